"""Approximate nearest-neighbour search on sign-magnitude codes, as Spark programs."""
