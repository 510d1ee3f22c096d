"""Compressed-vector near-copy engine on Spark DataFrames."""
