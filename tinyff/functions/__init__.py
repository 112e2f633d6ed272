"""Column functions: text, hashing, features."""
