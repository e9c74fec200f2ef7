"""Column expressions, UDFs, UDTFs and the SQL surface."""
