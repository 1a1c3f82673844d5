"""Scans and the trip, network and query fixtures built from the given tables."""
