"""Finds statistically significant relationships between spatio-temporal tables on Spark."""
