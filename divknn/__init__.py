"""Exact and probabilistic k-nearest-neighbour search under Bregman divergences, on Spark."""
