"""Operators on labelled facts and polynomials."""
