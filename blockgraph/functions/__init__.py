"""Column functions and user-defined functions, aggregates and table functions."""
