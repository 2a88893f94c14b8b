"""Similarity sketches of many sets under streams of insertions and deletions, on Spark DataFrames."""
