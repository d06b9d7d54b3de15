"""Streaming of the rank engine."""
