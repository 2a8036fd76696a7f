"""Multidimensional indexing, sampling, neighbour search and density mining on Spark."""
