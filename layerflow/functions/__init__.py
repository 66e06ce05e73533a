"""Column expressions, vector functions and weights."""
