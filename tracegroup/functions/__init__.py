"""functions of the grouping engine."""
