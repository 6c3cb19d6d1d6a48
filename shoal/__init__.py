"""Community detection on large weighted graphs, written for Spark DataFrames."""
