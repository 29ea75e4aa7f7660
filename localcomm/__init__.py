"""Local communities in attributed graphs, written for Spark DataFrames."""
