"""Index growth on streams."""
