"""Operators of the factorization, each a function from DataFrames to DataFrames."""
