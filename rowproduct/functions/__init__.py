"""Semirings, accumulator kernels and SQL functions."""
