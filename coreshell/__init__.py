"""Coreness of very large undirected graphs on Spark, and a subpackage of training-data operators."""
