"""Column functions: keys, text measures, vectors, coefficients."""
