"""functions of the contribution engine."""
