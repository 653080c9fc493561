"""Likelihood-driven graph clustering on Spark DataFrames."""

__version__ = "0.1.0"
