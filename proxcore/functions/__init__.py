"""User-defined functions, for SQL and DataFrames."""
