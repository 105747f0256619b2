"""Continuous distinct counts."""
