"""Expressions and numeric kernels the operators are built from."""
