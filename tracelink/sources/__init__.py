"""Traces derived from the given tables, readers and writers."""
