"""Column functions and the SQL surface."""
