"""Relational plans as SQL text of a dialect, and as DataFrames."""
