"""Streams over the query log and arriving vectors."""
