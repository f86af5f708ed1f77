"""Queries over the given tables, with the same question in SQL."""
