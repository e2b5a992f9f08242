"""Viewport-driven, error-bounded aggregation over tiles, on Spark DataFrames."""

__version__ = "0.1.0"
