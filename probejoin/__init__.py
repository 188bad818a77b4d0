"""Graph-pattern joins over two clustered triple indexes, on Spark DataFrames."""
