"""Iterative vertex-centric graph computation on Spark DataFrames."""
