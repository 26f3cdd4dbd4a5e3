"""Relational operators over graphs: joins, aggregations, windows, sets, orders."""
