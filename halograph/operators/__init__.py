"""Relational operators and kernels around the methods."""
