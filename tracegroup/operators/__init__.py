"""operators of the grouping engine."""
