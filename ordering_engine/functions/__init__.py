"""Column functions: hashes, order keys, curves."""
