"""Sources of the row-reordering engine."""
