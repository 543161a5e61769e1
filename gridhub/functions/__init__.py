"""functions of the grid clustering engine."""
