"""Readers, writers and the fixtures derived from the given tables."""
