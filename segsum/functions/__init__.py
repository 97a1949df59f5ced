"""Column functions, numpy kernels and error bounds."""
