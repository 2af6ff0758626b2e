"""Integer linear programs on the driver or in one task."""
