"""Exact and graph search, lifting, refining, thinning and measuring, as operators on DataFrames."""
