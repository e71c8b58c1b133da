"""Batch approximate nearest-neighbour search on Spark by counting collisions in subspaces."""
