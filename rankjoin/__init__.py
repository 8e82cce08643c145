"""Ranked enumeration of join answers on Spark DataFrames."""
