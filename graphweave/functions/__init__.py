"""Column functions on vectors and engine-neutral hashes."""
