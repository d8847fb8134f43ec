"""Column expressions and registered SQL functions."""
