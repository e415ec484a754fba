"""Queries: expressions, their types, their flat blocks, and the DataFrames these become."""
