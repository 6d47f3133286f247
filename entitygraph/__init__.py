"""Entity resolution as a graph problem, on Spark DataFrames."""
