"""Executors of conjunctive queries over DataFrames."""
