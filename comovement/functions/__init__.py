"""Column functions: distances and grid cells."""
