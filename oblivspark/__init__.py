"""Data-oblivious analytics on Spark DataFrames."""
