"""Column expressions, UDFs and table functions for SQL users."""
