"""sources of the connectivity engine."""
