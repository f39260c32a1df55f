"""Relationship queries, corpora and workloads built from the operators."""
