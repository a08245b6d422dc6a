"""Column functions: text to sequences, and sequences to grams."""
