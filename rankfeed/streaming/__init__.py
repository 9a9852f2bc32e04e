"""Gradients from streams (``days``)."""
