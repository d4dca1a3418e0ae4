"""Scalar functions usable in rules."""
