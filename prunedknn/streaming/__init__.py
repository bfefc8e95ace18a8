"""Rows that arrive: appended to a table, or windowed."""
