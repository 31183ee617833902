"""SQL functions: scalar, aggregate and table functions."""
