"""Grouping of crash reports by their stack traces, on Spark DataFrames."""
