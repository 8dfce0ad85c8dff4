"""Approximate similarity joins by locality-sensitive hashing, for Spark DataFrames."""
