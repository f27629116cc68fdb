"""Column expressions, Arrow functions and table functions."""
