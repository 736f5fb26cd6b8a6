"""Exact similarity search over data series, written for Spark DataFrames."""
