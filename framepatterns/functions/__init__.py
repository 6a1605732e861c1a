"""Column functions and user-defined functions around the operators."""
