"""Column functions: portable hashes, losses, vectors."""
