"""Text of a graph query to its syntax tree."""
