"""Kernels on single graphs and columns built from native expressions."""
