"""Combiners and user functions."""
