"""Graph queries over native tables, for Spark."""
