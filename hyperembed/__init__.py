"""Attributed-hypergraph embedding on Spark DataFrames."""
