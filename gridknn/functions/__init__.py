"""Column expressions: distances, cell numbers, votes."""
