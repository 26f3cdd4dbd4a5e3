"""Graphs derived from tables and generated ones."""
