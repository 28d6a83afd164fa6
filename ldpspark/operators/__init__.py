"""Report mechanisms (the client's side) and estimators (the collector's)."""
