"""streaming of the connectivity engine."""
