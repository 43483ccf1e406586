"""sources of the contribution engine."""
