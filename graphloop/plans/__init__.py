"""Queries, their algebra and its translation to DataFrames."""
