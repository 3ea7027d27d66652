"""Column functions, UDFs, the SQL front end and the DataFrame API."""
