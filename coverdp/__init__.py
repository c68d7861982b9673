"""Pattern search in large planar graphs, written for Spark DataFrames."""
