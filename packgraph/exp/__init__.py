"""Experiments re-expressed on the given tables."""
