"""Dynamic random walks on Spark DataFrames."""
