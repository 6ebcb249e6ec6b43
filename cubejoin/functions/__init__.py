"""SQL-visible functions."""
