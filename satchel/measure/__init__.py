"""Timing, ratios, coverage, selectivity, guarantees."""
