"""Aggregates over streams."""
