"""Column functions, also registered for SQL."""
