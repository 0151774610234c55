"""Column expressions and pure formulas."""
