"""Incremental query engine on PySpark DataFrames."""
