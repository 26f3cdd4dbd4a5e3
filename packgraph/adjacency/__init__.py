"""Adjacency data: permuters (labels) and transformers (bits of a list)."""
