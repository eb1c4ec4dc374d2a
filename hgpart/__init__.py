"""Partitioning of weighted directed hypergraphs under size and inbound limits, on Spark DataFrames."""
