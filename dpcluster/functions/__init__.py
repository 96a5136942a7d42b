"""Column functions: keyed noise, normalisation, and a registry for SQL."""
