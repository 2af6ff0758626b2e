"""Offline partitionings and their representatives."""
