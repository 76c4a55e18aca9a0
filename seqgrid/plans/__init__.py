"""Search for the best grid, and baselines."""
