"""Cell tables of streams."""
