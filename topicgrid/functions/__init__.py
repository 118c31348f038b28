"""Column functions, SQL functions and UDFs."""
