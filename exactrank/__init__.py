"""Exact order statistics on large distributed data, on Spark DataFrames."""
