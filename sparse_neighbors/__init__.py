"""Exact k-nearest-neighbour joins of sparse high-dimensional vectors on Spark."""
