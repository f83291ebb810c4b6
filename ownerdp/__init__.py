"""Aggregate queries with owner-level differential privacy on Spark DataFrames."""
