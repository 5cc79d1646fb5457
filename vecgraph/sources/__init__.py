"""Readers, writers and the vector sets derived from the given tables."""
