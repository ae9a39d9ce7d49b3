"""Functions for DataFrames and SQL."""
