"""Column functions and compactions."""
