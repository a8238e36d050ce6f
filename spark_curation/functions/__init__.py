"""Column functions: text, tokens, hashing."""
