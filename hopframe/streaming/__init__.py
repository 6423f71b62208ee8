"""The event table as a stream."""
