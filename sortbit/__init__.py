"""Sorted, word-compressed bitmap indexes on Spark DataFrames."""
