"""Readers, writers and graphs of the given tables."""
