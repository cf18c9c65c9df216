"""Column helpers, vectorised kernels and SQL functions."""
