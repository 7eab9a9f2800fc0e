"""Column expressions: distances, grid cells, sampling keys."""
