"""Constants, keyed randomness and SQL functions."""
