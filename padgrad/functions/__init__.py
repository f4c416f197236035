"""Column functions: fixed-point arithmetic, keys, vectors."""
