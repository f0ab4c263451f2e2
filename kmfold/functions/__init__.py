"""Column functions: clustering features, vector algebra, hashing, cost."""
