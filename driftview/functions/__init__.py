"""Feature functions, vectors, and SQL functions."""
