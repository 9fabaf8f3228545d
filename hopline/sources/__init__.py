"""Readers, writers and the graph recipes over the given tables."""
