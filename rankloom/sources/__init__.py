"""Sources of the rank engine."""
