"""Column functions and their NumPy twins."""
