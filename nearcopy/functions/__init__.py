"""Column expressions, features and losses."""
