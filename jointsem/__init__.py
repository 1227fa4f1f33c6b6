"""Semantic operators that read a text dataset as a whole, on Spark DataFrames."""
