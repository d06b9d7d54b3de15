"""Operators of the rank engine."""
