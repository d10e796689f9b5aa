"""Arrow kernels and the choice among plans."""
