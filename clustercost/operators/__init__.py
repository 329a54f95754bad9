"""Operators of the clustering-cost engine, one module a family."""
