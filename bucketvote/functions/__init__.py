"""Column-level building blocks: features, hashes, similarities."""
