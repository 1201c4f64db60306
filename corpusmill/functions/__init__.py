"""Vectorised functions that run inside Arrow batches."""
