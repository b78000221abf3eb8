"""Functions for use in SQL and DataFrames."""
