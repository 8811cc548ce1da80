"""Column functions, draws and user-defined functions."""
