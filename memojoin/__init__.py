"""Memoised multiway joins on Spark DataFrames."""
