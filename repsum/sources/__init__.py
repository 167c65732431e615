"""Readers, sinks and the query logs derived from the given tables."""
