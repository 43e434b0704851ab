"""Operators over graphs, paths and predictions."""
