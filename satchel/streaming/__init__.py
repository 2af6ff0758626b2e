"""Packages over event streams."""
