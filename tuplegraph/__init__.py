"""Keyword search over tuple graphs, on Spark."""
