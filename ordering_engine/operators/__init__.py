"""Relational operators around the methods."""
