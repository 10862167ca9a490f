"""streaming of the grouping engine."""
