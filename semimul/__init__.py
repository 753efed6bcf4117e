"""Sparse semiring matrix products on Spark DataFrames."""
