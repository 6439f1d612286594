"""Subspace-collision nearest-neighbour search and training-data operators on Spark DataFrames."""
