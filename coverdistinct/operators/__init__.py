"""Samplers, counters, spectra, probes, estimators and planners."""
