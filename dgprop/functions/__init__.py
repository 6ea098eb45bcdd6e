"""Column functions: vectors, portable hashes, Python functions."""
