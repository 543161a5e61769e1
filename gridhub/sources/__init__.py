"""sources of the grid clustering engine."""
