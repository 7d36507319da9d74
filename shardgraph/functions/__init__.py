"""Column functions and user-defined functions over vectors."""
