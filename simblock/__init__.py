"""Blocking for entity matching and deduplication on Spark."""
