"""streaming of the grid clustering engine."""
