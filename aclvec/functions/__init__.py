"""Column functions: portable hash, vectors, cost and recall models."""
