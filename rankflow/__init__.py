"""Graph ranks kept fresh under batches of edge changes, on Spark DataFrames."""
