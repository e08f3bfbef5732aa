"""Column expressions: hashing, probability model, estimators, pair likelihood."""
