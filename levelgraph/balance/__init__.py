"""Work division: slices, ranges and pulling."""
