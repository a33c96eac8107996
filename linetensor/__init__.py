"""Sparse-tensor analytics on Spark DataFrames: one packed index per non-zero, one copy for all modes."""

__version__ = "0.1.0"
