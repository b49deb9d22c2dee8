"""Kernels and SQL functions."""
