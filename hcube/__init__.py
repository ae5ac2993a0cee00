"""Exact sums over hierarchical data cubes, on Spark DataFrames."""
