"""Table union search over vector sets, on Spark DataFrames."""
