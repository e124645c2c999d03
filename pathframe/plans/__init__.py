"""Logical plans over sets of paths, their rewriting, execution and language."""
