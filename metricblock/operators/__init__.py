"""Embedding, search, blocking, matching, baselines and measures on DataFrames."""
