"""Coreness of graphs that arrive as streams."""
