"""Column functions and measures."""
