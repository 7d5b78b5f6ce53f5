"""Column functions, vectorised UDFs and table functions."""
