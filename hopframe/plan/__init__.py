"""Graph plans: hop classification, bindings and the relational plan they become."""
