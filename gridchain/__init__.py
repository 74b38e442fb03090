"""Chained sparse/dense products on Spark DataFrames."""
