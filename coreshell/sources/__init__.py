"""Readers and writers of graphs and tables."""
