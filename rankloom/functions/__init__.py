"""Functions of the rank engine."""
