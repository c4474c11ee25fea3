"""Approximate (p,q)-biclique counting on Spark DataFrames, with exact and sampling baselines."""
