"""Placing unseen sequences on a fixed grid."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqgrid.functions.mathx import ln_fact, ln_gamma_step
from seqgrid.operators.grid import Grid


def _laid(g: Grid, new: DataFrame) -> DataFrame:
    """New points with the grid's intervals and event clusters; times outside go to the first or last interval, unknown events drop out."""
    t = g.t_parts.select("t_part", "t_lo", "t_hi")
    w = Window.orderBy("t_part")  # one row for each interval of the grid
    high = F.lit(None).cast(new.schema["t"].dataType)
    bounds = t.select("t_part", F.lag("t_hi").over(w).alias("t_lo"), F.when(F.lead("t_part").over(w).isNotNull(), F.col("t_hi")).otherwise(high).alias("t_hi"))
    hit = (F.col("t_lo").isNull() | (F.col("t") > F.col("t_lo"))) & (F.col("t_hi").isNull() | (F.col("t") <= F.col("t_hi")))
    return new.join(F.broadcast(bounds), hit).drop("t_lo", "t_hi").join(g.e_values.select(F.col("value").alias("e"), F.col("part").alias("e_part")), "e")


def nearest(g: Grid, new: DataFrame) -> DataFrame:
    """(s, part, delta): the cluster in which each new sequence costs least."""
    profile = _laid(g, new).groupBy("s", "t_part", "e_part").agg(F.sum("n").cast("long").alias("x"))
    base = profile.groupBy("s").agg(F.sum("x").alias("nx"), F.sum(-ln_fact(F.col("x"))).alias("base"))
    hit = profile.join(g.cells, ["t_part", "e_part"]).groupBy("s", F.col("s_part").alias("part")).agg(F.sum(ln_fact(F.col("x")) + ln_fact(F.col("n")) - ln_fact(F.col("x") + F.col("n"))).alias("hit"))
    p = g.parts("S")
    all_ = base.join(F.broadcast(p))
    level = ln_gamma_step(F.col("n_values") + 1, F.col("n_points") + F.col("nx")) - ln_gamma_step(F.col("n_values"), F.col("n_points"))
    d = all_.join(hit, ["s", "part"], "left").withColumn("delta", level + F.col("base") + F.coalesce("hit", F.lit(0.0)))
    return d.groupBy("s").agg(F.min_by("part", F.struct("delta", "part")).alias("part"), F.min("delta").alias("delta"))


def unseen(g: Grid, new: DataFrame) -> DataFrame:
    """(dim, value): sequences and events of the new points that the grid doesn't know."""
    s = new.select(F.col("s").cast("string").alias("value")).distinct().join(g.s_values.select(F.col("value").cast("string").alias("value")), "value", "left_anti")
    e = new.select(F.col("e").cast("string").alias("value")).distinct().join(g.e_values.select(F.col("value").cast("string").alias("value")), "value", "left_anti")
    return s.select(F.lit("S").alias("dim"), "value").unionByName(e.select(F.lit("E").alias("dim"), "value"))
