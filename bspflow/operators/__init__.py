"""Relational and row-program operators around the methods."""
