"""Functions for SQL users."""
