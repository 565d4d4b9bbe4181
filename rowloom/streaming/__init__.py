"""Streaming of the row-reordering engine."""
