"""From package queries to linear rows and coefficient frames."""
