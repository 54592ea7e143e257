"""Schema evolution of triple graphs under inference rules, on Spark DataFrames."""
