"""Relational building blocks around the methods."""
