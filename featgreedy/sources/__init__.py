"""Table readers, block stores and planted data."""
