"""Column functions: complex arithmetic, basis indices, checks."""
