"""Structured Streaming forms of the harness and its live measures."""
