"""Column functions and semantic functions."""
