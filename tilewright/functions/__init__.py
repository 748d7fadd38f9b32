"""Column expressions: box geometry, space-filling curves, well-known text."""
