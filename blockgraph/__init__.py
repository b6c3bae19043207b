"""Block-wise graph analytics on Spark DataFrames."""
