"""Alignment kernels and column functions."""
