"""Nearest-neighbour search under numeric interval constraints, on Spark."""
