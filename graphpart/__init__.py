"""Balanced k-way graph partitioning on Spark DataFrames."""
