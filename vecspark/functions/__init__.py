"""Column functions, numpy kernels and registered user functions."""
