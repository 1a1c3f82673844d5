"""Compression of trips on a road network, and queries on the packed form, written for Spark."""
