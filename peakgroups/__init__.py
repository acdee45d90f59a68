"""Stable, overlapping, hierarchical clustering of weighted networks on Spark DataFrames."""
