"""Digit-distribution sorting and ordering engine on PySpark DataFrames."""
