"""Sorted, compressed bitmap indexes on Spark DataFrames."""
