"""plans of the contribution engine."""
