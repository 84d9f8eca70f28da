"""Column expressions: log space, hashes that every engine repeats."""
