"""Exact marginal inference over Spark DataFrames by bag-wise multiway joins."""
