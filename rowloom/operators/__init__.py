"""Operators of the row-reordering engine."""
