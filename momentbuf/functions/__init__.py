"""Column expressions: aggregate specifications, interpolation weights, scalars."""
