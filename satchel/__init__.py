"""satchel: package queries (multisets of tuples under linear global conditions) on Spark."""
