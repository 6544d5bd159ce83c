"""Layouts and darts: what is prepared once for a data set."""
