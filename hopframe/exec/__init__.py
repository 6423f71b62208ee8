"""Running compiled queries on a Spark session."""
