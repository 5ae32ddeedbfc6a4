"""Mixture models as relations, trained and queried with Spark DataFrames."""

__version__ = "0.1.0"
