"""Object-level nearest-neighbour search on Spark DataFrames."""
