"""Approximate-key analytics on PySpark DataFrames."""
