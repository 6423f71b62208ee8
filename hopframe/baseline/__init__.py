"""What the engine is compared with: re-encoded graphs, per-tuple traversal, naive translations, vertex programs."""
