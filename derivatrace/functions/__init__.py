"""Subpackage of pure column expressions: labels and monomials."""
