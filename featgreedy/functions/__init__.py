"""Column functions: seeded draws, array algebra, families, text."""
