"""Structured Streaming over traces."""
