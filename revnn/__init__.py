"""revnn: reverse-k-nearest-neighbour analytics on Spark DataFrames."""
