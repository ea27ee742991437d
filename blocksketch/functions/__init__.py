"""Column functions: the hash family behind every sketch."""
