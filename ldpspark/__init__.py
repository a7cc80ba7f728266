"""Locally private counting and heavy hitters on Spark DataFrames."""

__version__ = "0.1.0"
