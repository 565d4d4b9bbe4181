"""Functions of the row-reordering engine."""
