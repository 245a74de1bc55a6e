"""Compressed-gradient descent and its measures on Spark DataFrames."""
