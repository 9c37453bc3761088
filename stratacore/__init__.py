"""Core decomposition of very large graphs on Spark DataFrames."""
