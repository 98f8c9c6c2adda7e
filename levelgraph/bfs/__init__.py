"""Direction-switching breadth-first search."""
