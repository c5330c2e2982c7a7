"""Lossy grid compression and compressed-domain analysis on Spark DataFrames."""

__version__ = "0.1.0"
