"""Registered plans: the queries of the catalogue and their SQL."""
