"""plans of the connectivity engine."""
