"""Collection from streams: snapshots, one report per user and period, and training in micro-batches."""
