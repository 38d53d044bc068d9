"""Matrices from tables, text and kernels."""
