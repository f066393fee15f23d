"""Interactive association mining on Spark DataFrames."""
