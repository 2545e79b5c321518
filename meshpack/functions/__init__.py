"""Expressions and numpy kernels."""
