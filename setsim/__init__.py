"""Exact set-similarity joins with hashed-bitmap pruning on Spark DataFrames."""
