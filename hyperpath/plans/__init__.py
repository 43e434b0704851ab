"""Experiments and the registry of queries."""
