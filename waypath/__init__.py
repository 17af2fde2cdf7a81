"""Paths through similarity networks that are never built in full, on Spark DataFrames."""
