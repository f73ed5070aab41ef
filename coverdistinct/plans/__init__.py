"""Experiment workloads, the query catalogue and plan checks."""
