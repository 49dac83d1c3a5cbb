"""Column functions: portable hashes, means, scalar helpers."""
