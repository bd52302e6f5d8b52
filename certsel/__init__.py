"""Guaranteed approximate selection over very large tables, on Spark DataFrames."""
