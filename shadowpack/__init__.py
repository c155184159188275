"""Budgeted selection at scale by pricing shared resources, on Spark DataFrames."""
