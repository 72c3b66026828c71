"""Column functions: hashing."""
