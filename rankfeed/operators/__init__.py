"""Gradient operators: products, reductions, compressors, feedback, measures."""
