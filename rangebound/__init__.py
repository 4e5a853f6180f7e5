"""Bounds-preserving order operators over uncertain data, on Spark DataFrames."""
