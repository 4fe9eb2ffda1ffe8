"""Constrained geo-social group search on Spark DataFrames."""
