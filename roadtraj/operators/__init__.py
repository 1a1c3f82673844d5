"""Compression stages, queries on packed trips, baselines and measures."""
