"""Partition-aware graph analytics on Spark DataFrames."""
