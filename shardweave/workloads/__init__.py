"""Experiments and operator queries on the given tables."""
