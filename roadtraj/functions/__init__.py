"""Column expressions: interpolation and geometry in exact integers."""
