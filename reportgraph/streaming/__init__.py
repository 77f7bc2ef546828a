"""Report events as streams."""
