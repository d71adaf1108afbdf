"""Column functions and SQL expressions."""
