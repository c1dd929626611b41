"""Column functions: hashing, tokens, vectors, spans."""
