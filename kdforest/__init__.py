"""Exact nearest-neighbour search over points that change in batches, for Spark."""
