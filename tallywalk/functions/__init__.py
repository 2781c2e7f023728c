"""Column expressions: hashes, registers and their estimators, bounds and sizes."""
