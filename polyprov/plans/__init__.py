"""The way from SQL and DataFrames to annotated plans."""
