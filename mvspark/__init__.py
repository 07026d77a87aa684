"""Similarity search over multi-vector objects, on Spark DataFrames."""
