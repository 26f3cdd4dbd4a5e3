"""Checks on physical plans."""
