"""Source-target reliability on uncertain graphs, written for Spark DataFrames."""
