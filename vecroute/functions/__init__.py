"""Scalar functions over vectors, numpy kernels and measures."""
