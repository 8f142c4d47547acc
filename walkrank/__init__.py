"""Certified ranking of graph nodes by attenuated walk counts, on Spark DataFrames."""
