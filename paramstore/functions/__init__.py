"""Column expressions, bit patterns and kernels."""
