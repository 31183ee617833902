"""Readers, writers and the given tables as matrices, tensors and trade graphs."""
