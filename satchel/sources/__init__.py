"""Readers, writers, joins before packaging."""
