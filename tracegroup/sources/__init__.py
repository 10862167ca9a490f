"""sources of the grouping engine."""
