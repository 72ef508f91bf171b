"""Column functions: normalisation, hashing and the retention budget."""
