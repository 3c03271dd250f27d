"""Message codec and SQL functions."""
