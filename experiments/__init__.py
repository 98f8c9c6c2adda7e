"""Experiments that need sessions or timings of their own."""
