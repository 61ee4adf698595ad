"""Retrieval over two-tier hierarchical graphs, built on Spark DataFrames."""
