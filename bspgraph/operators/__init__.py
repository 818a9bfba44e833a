"""Relational operators around the graphs."""
