"""Column expressions and Arrow functions over interval labels."""
