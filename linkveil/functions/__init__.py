"""Column expressions: text, keyed hashing, bits, and their SQL names."""
