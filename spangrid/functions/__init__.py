"""Column functions, SQL functions and table functions over intervals."""
