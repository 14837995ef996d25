"""Semiring graph engine on Spark DataFrames."""
