"""Column functions over vectors and code strings."""
