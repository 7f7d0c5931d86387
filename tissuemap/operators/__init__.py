"""Relational operators in the long layout: one row per coefficient."""
