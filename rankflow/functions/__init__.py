"""Measures, user functions and their registration for SQL."""
