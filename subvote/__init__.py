"""Adaptive subspace-collision nearest-neighbour search and the operators around it, on Spark."""
