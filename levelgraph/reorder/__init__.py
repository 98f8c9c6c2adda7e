"""Vertex orders, components and locality measures."""
