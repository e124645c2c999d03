"""Column functions over path rows."""
