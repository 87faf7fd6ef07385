"""Exact probabilistic rule reasoning over uncertain tables, on Spark DataFrames."""
