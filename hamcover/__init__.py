"""Exact near-neighbour search over binary codes in Hamming space, on Spark DataFrames."""
