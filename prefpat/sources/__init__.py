"""Readers, writers and the ten encodings of the given tables."""
