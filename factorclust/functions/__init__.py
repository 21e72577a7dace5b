"""Column functions and closed forms."""
