"""pathframe: sets of graph paths as Spark DataFrames."""
