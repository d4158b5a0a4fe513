"""Vectors for the text values of relational tables, learned with Spark DataFrames."""
