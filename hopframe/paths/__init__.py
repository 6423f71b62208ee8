"""Path forms beyond flat chains: frontier loops, pointer doubling, shared prefixes, shortest paths."""
