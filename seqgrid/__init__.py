"""seqgrid: groups event sequences, time and events at once in a three-way grid, on Spark.

functions   numeric columns, time keys, SQL functions
sources     points from tables, files and generators; saving and loading of grids
operators   grids, their score, merges, moves, views, hierarchies, accuracy
plans       the search: in-memory kernel, distributed rounds, restarts, baselines
streaming   watermarked points, windows, drift of a fixed grid
"""
