"""Offset structures: where each vertex's list starts."""
