"""Sources of the private frequency engine."""
