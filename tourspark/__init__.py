"""Partition-centric closed circuits over large even graphs, on Spark DataFrames."""
