"""Numeric columns, time keys and SQL functions."""
