"""How typical a value is of its cluster: the mean change of cost, weighted by mass, of sending it to the others."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqgrid.operators.grid import Grid
from seqgrid.operators.refine import move_deltas


def typicality(g: Grid, dim: str) -> DataFrame:
    """(dim, part, value, n, tau); tau is null where there is one cluster only."""
    N = g.shape().N
    mass = g.parts(dim).select(F.col("part").alias("target"), (F.col("n_points") / F.lit(max(N, 1))).alias("p"))
    own = g.parts(dim).select("part", (F.col("n_points") / F.lit(max(N, 1))).alias("p_own"))
    tau = move_deltas(g, dim).join(F.broadcast(mass), "target").groupBy("value").agg(F.sum(F.col("p") * F.col("delta")).alias("sum"))
    return g.values(dim).join(F.broadcast(own), "part").join(tau, "value", "left").select(F.lit(dim).alias("dim"), "part", "value", "n", (F.col("sum") / (1 - F.col("p_own"))).alias("tau"))


def top(g: Grid, dim: str, k: int = 5) -> DataFrame:
    """(dim, part, rank, value, n, tau) of the k most typical values of each cluster."""
    w = Window.partitionBy("part").orderBy(F.col("tau").desc_nulls_last(), "value")
    return typicality(g, dim).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
