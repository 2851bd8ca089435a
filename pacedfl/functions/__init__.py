"""Columns and SQL functions."""
