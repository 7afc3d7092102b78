"""Functions of the private frequency engine."""
