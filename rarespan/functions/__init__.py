"""Column-level functions and constant tables."""
