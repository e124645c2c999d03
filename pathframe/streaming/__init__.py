"""Edges and short paths from event streams."""
