"""Evaluation methods: baselines, whole solve, coarse-fine, remedies."""
