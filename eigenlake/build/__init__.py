"""Operators and spectra built from tables."""
