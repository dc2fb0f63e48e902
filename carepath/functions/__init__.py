"""Column expressions, SQL functions, UDFs and table functions."""
