"""Kernels and the operators around them."""
