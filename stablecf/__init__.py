"""Numerically stable cluster-feature analytics on Spark DataFrames."""
