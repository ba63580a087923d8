"""Exact, reproducible floating-point aggregation on Spark DataFrames."""
