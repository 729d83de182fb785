"""Column functions: hash families and sizing formulas."""
