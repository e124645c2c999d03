"""Operators over sets of paths."""
