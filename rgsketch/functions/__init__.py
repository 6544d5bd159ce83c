"""Column functions: counter-based draws, universal hashes, SQL registration."""
