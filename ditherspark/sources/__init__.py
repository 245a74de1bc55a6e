"""Reading the input tables."""
