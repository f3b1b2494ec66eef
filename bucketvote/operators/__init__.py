"""Index, sketch, search, baselines, near-duplicates."""
