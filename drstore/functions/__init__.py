"""Functions and table functions for SQL."""
