"""Gradient sources over the given tables."""
