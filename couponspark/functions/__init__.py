"""Column expressions: hashing, estimators of one row, theory."""
