"""Column functions: seeded draws, vectors, text."""
