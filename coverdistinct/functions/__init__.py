"""Portable hashes, accuracy formulas and SQL functions."""
