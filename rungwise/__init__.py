"""Local-access compression of very long symbol sequences, on Spark DataFrames."""
