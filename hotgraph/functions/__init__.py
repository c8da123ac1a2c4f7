"""Column expressions of the method, and the same values as user-defined functions."""
