"""Column and table functions on text."""
