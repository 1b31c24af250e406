"""Column functions: kernels, quantisation, curves."""
