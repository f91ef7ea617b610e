"""Column functions, user-defined functions and small dense kernels."""
