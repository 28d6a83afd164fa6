"""Training-data operators: joins, filters, formatting, mixing and sharding of text corpora.

Nothing else in the library imports this subpackage. Every operator takes
DataFrames and returns DataFrames; ``queries`` binds them to the given tables.
"""
