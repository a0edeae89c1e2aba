"""pathweave: regular path queries that return paths, on Spark DataFrames."""
