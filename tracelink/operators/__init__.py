"""Operators over traces, signatures and neighbour lists."""
