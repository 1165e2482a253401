"""operators of the connectivity engine."""
