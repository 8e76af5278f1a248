"""Column functions: geometry, and SQL functions of the same names."""
