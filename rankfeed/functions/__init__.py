"""Scalar functions: reproducible draws."""
