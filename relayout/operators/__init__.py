"""Operators that move or multiply data, and the relational surface around them."""
