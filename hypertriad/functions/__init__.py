"""Column functions and relational helpers."""
