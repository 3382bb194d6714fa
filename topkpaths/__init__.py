"""Top-k heaviest simple paths of a fixed length, on Spark DataFrames."""
