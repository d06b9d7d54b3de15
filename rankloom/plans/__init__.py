"""Plans of the rank engine."""
