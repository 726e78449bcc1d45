"""Column expressions and measures."""
