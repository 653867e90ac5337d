"""Exact substring search over the most recent part of symbol streams, on Spark."""
