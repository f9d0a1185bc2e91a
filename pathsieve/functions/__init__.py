"""Column functions and the pattern language."""
