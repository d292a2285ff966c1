"""Functions and views for SQL."""
