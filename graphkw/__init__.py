"""Rooted keyword search over large graphs, on Spark DataFrames."""
