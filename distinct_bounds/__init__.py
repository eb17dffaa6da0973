"""Approximate distinct counting with non-asymptotic intervals, on Spark DataFrames."""
