"""revnet: batch reverse k-nearest-neighbour queries on road networks, on Spark DataFrames."""
