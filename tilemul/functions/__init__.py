"""Semirings and local tile kernels."""
