"""Relational operators around the blocking methods."""
