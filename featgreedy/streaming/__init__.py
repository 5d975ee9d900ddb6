"""Row segments as streams."""
