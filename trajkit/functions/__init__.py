"""Column builders and Python functions."""
