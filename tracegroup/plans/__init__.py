"""plans of the grouping engine."""
