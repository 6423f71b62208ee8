"""Relational operators around the graph engine."""
