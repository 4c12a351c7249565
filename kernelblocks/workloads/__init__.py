"""Experiments on the given tables."""
