"""Hash functions, Arrow and SQL functions."""
