"""Recompute-on-read vector search and its baselines on Spark DataFrames."""
