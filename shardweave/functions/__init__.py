"""Distances and other column functions, for DataFrames and for SQL."""
