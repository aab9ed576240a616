"""Range-filtered nearest-neighbour search on Spark."""
