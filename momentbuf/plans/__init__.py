"""Cost formulas, choice of method, and the SQL surface."""
