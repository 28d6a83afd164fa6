"""Schemas of private tuples, views over the given tables, and experiment plans."""
