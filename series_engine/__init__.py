"""k-nearest-neighbour search over large collections of equal-length series, on Spark."""
