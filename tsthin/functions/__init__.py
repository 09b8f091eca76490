"""SQL-callable functions and table functions."""
