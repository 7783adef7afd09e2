"""Streaming operators over event time."""
