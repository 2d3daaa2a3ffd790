"""Compressed and plain tile formats. Each is a module of pure NumPy functions and one line in `registry`."""
