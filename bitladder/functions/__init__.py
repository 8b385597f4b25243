"""Column expressions, SQL functions and Arrow functions."""
