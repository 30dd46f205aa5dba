"""Approximate entity resolution in a landmark space, on Spark DataFrames."""
