"""Operators on packages."""
