"""Column functions on query texts."""
