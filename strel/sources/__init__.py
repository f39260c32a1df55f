"""Input tables and their roles."""
