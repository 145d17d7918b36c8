"""Balanced graph partitioning and size-bounded clustering on Spark DataFrames."""

__version__ = "0.1.0"
