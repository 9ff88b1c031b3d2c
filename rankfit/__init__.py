"""Approximate ranks and quantiles for very large columns, on Spark DataFrames."""

__version__ = "0.1.0"
