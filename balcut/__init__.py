"""Perfectly balanced graph partitioning on Spark DataFrames."""
