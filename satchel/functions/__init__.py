"""Aggregates and the query builder."""
