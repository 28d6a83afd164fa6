"""The same answers as DuckDB text: written in long form, with the constants of the library but none of its code paths."""
