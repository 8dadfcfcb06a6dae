"""Column expressions and measures used around the joins."""
