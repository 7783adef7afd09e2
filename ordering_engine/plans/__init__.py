"""Distributed sorting, ranking and selection methods."""
