"""Ranked answers to theta-joins, planned as ordinary Spark DataFrames."""
