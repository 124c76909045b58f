"""Ranked, standing keyword queries over linked tables, on Spark DataFrames."""
