"""Column functions, bounds and the SQL surface."""
