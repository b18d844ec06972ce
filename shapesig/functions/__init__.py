"""Column expressions, array kernels, closed-form theory and SQL functions."""
