"""Relational operators around the solver."""
