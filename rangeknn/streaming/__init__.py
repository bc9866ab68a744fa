"""Queries as streams."""
