"""Readers and the corpora rendered from the given tables."""
