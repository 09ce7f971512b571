"""Column expressions: hashing, features, scores, networks."""
