"""Column functions: text, grams, hashing, sizing, measures."""
