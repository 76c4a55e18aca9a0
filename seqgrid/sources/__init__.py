"""Points from tables, files and generators; saved grids."""
