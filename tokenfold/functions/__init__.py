"""Expressions and array kernels."""
