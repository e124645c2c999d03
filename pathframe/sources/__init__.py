"""Graphs from tables, and sinks for sets of paths."""
