"""Void-feature analytics over very large particle data, on Spark DataFrames."""
