"""Column functions and hash-based randomness."""
