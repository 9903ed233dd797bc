"""netan: network analysis on Spark DataFrames."""
