"""Balanced partitioning of large skewed graphs with Spark DataFrames."""
