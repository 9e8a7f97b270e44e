"""Column functions: dominance, vectors, cost models."""
