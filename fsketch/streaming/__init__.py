"""Sketches over event streams."""
