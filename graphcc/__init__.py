"""graphcc: connected components of very large graphs on Spark DataFrames."""
