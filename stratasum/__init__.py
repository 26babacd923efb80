"""Recursive aggregates over sets of known size, on Spark."""
