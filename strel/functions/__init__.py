"""Column functions and functions for SQL."""
