"""Applications of breadth-first search."""
