"""Balanced graph partitioning on Spark DataFrames."""
