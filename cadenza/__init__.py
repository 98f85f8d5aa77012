"""Similarity search over series under spectral transformations, on Spark DataFrames."""
