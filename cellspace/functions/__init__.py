"""Column expressions, shapes, curves and SQL-callable functions."""
