"""Graphs and the methods that compute their coreness."""
