"""Column expressions, codecs in numpy, and functions for SQL."""
