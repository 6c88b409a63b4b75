"""Local kernels, column expressions and SQL functions."""
