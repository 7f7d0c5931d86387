"""Column expressions: complex numbers, vectors, hashing."""
