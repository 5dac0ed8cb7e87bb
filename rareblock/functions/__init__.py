"""Column expressions: text, hashing, MinHash."""
