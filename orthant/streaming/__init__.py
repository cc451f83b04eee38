"""Matrices and factors from streams."""
