"""Column expressions: hashing, bands, probability and loss formulas."""
