"""Sketches of growing data."""
