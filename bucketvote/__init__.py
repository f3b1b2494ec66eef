"""Similarity search over sparse sets by locality-sensitive keys and mergeable vote-count sketches, as DataFrame plans."""
