"""Catalogue of queries: every method as a plan on the given tables, with its SQL where SQL can say it."""
