"""Linking of tables through contextual graphs, on Spark DataFrames."""
