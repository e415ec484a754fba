"""Patterns: the algebra of partial values, and its distributed form."""
