"""Distances as Column expressions and as NumPy block kernels, and local linear algebra."""
