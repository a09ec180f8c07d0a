"""Graphs out of the given tables and synthetic ones."""
