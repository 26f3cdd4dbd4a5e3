"""Scalar functions and the SQL surface."""
