"""Metric nearest-neighbour search on Spark DataFrames."""
