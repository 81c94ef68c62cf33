"""Column formulas and measures."""
