"""Grids over the given tables, and anchor tables on storage."""
