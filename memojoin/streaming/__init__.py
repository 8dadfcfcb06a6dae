"""Edges from streams and incremental counts."""
