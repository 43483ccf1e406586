"""operators of the contribution engine."""
