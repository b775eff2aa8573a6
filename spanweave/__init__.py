"""spanweave: bridges, blocks and tree primitives of very large graphs held as Spark DataFrames."""
