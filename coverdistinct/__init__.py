"""Distinct counting from sampled streams on Spark."""
