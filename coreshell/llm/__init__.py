"""Operators of a large-scale training-data pipeline.

Every operator takes plain DataFrames, reads only the columns it names (other
columns may have any name), treats a null text as the empty text and keeps a
defined result for empty tables, repeated rows and ties.
"""
