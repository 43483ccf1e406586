"""streaming of the contribution engine."""
