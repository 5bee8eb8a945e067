"""The experiments on the given tables, with their SQL."""
