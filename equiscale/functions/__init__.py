"""Column functions and SQL functions of the joins."""
