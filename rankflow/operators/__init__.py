"""Snapshots, batches, marking, iteration and the update methods."""
