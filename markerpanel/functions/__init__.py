"""Column functions: sequences, kernels, formatting."""
