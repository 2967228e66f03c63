"""Data-independent relational analytics on Spark DataFrames."""
