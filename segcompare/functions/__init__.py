"""Column and SQL functions on rings."""
