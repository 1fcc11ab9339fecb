"""Weighted-space rebalancing on Spark DataFrames."""
