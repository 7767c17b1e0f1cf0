"""Approximate string matching for data cleaning, on Spark DataFrames."""
