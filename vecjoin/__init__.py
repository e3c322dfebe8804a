"""Similarity joins over large collections of vectors, on Spark DataFrames."""
