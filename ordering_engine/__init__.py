"""Ordering engine: distributed sorting, ranking and selection methods on Spark DataFrames."""
