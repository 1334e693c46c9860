"""Distributed implicit matrix factorization on Spark DataFrames."""
