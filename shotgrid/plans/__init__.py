"""Relational forms of what users of range images ask for: scans, joins, aggregates, windows, set operations, scalar functions."""
