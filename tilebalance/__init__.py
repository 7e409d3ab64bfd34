"""Skew-aware spatial load balancing on Spark DataFrames."""
