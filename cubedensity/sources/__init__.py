"""Event sets, readers and generated grids."""
