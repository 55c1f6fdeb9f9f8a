"""Approximate counting of tree-shaped patterns in very large graphs, on Spark DataFrames."""
