"""Column functions, formulas and SQL-callable functions."""
