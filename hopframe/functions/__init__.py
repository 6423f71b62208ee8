"""User-defined functions: the ways out of the built-in ones, each in Arrow batches where Spark allows."""
