"""Operators of the similarity engine."""
