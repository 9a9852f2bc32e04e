"""Cost formulas."""
