"""Compression and search of inverted-index posting lists on Spark DataFrames."""
