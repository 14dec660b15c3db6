"""Column expressions and registered functions: encoders, labels, losses, vectors."""
