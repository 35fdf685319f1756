"""Approximate top-k graph queries over knowledge graphs in Spark DataFrames."""
