"""Graph-specific rewrites that a relational optimizer lacks: factorized counting, cyclic patterns, hop order."""
