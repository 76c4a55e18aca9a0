"""Generators of planted patterns of any size: a map over spark.range, no input and no shuffle but the folding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.operators.grid import Grid
from seqgrid.sources import points, workloads


def _uniform(seed: int, k: int):  # noqa: ANN202
    return (F.pmod(F.xxhash64(F.col("id"), F.lit(seed * 16 + k)), F.lit(1 << 40))) / float(1 << 40)


def _events(group, eta: float, seed: int):  # noqa: ANN001, ANN202
    noisy = _uniform(seed, 2) < eta
    other = (group * 3 + 3 + F.floor(_uniform(seed, 3) * 9)) % 12
    return F.when(noisy, other).otherwise(group * 3 + F.floor(_uniform(seed, 4) * 3)).cast("int")


def two_patterns(spark: SparkSession, n: int, cm: int = 10, eta: float = 0.0, seed: int = 0, integer_time: bool = False) -> DataFrame:
    """n points of 2 * cm sequences, even ones of the first pattern; time uniform on [0, 1000]."""
    df = spark.range(n).select("id", F.floor(_uniform(seed, 0) * 2 * cm).cast("long").alias("s"), (_uniform(seed, 1) * 1000).alias("x"))
    lo = lambda cuts: sum(((F.col("x") > c).cast("int") for c in cuts), F.lit(0))
    group = F.when(F.col("s") % 2 == 0, lo(workloads.CUTS[0])).otherwise(3 - lo(workloads.CUTS[1]))
    t = F.floor("x").cast("long") if integer_time else F.col("x")
    return points.from_table(df.select("s", t.alias("t"), _events(group, eta, seed).alias("e")), "s", "t", "e")


def many_patterns(spark: SparkSession, n: int, patterns: int = 5, cm: int = 10, eta: float = 0.0, seed: int = 0) -> DataFrame:
    df = spark.range(n).select("id", F.floor(_uniform(seed, 0) * patterns * cm).cast("long").alias("s"), (_uniform(seed, 1) * 1000).alias("t"))
    p = F.col("s") % patterns
    group = (F.floor(F.pmod(F.col("t") + p * 100, F.lit(1000.0)) / 250) + p) % 4
    return points.from_table(df.select("s", "t", _events(group, eta, seed).alias("e")), "s", "t", "e")


def truth_grid(p: DataFrame) -> Grid:
    return workloads.truth_grid(p, scale=1)
