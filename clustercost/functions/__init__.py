"""Functions for SQL: scalar, aggregate and table functions."""
