"""Exact all-pairs similarity joins over sets, multisets and vectors, on Spark DataFrames."""
