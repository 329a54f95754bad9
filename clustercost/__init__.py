"""Correlation-clustering cost engine on PySpark DataFrames."""
