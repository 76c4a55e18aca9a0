"""Grids, score, merges, moves, views, hierarchies and accuracy."""
