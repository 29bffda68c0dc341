"""Code provenance and weakness search on Spark DataFrames."""
