"""Approximate nearest-neighbour search with voting forests, on Spark DataFrames."""
