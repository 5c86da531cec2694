"""Weighted-diameter estimation on Spark DataFrames, with graph baselines and measures."""
