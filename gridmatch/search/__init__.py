"""Top-k region search."""
