"""Latency, growth, coverage, parity, re-encoding tax and plan shape."""
