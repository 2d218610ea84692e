"""Structured Streaming forms of the incremental methods."""
