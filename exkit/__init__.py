"""Shuffle strategies as library choices over Spark DataFrames, with the operators around them."""
