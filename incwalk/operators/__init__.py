"""Queries over graphs and tables, by category, each with the SQL that checks it."""
