"""Workload queries and the statements that check them."""
