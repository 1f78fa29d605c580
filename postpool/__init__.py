"""Compressed positional inverted indexes that grow document by document, on Spark DataFrames."""
