"""Algebra operators over DataFrames."""
