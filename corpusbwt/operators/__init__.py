"""Relational operators of index construction and search."""
