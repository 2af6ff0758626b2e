"""Workloads on the given tables."""
