"""Clustering of very large weighted graphs by synchronous local moving, on Spark DataFrames."""
