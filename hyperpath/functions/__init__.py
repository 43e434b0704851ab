"""Column functions, UDFs and SQL registrations."""
