"""Operators of the private frequency engine."""
