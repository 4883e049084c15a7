"""Column expressions: indices, hashing, discretising, log sums."""
