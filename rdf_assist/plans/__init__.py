"""Queries: their parts, their text and their compilation to DataFrames."""
