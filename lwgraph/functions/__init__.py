"""functions of the connectivity engine."""
