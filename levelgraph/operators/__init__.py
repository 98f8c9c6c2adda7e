"""Relational operators around graphs."""
