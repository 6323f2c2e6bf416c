"""annspark: proximity-graph nearest-neighbour search and corpus operators on Spark."""
