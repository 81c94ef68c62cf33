"""Relational operators around rank tables."""
