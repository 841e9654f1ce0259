"""Column functions and the UDF surface."""
