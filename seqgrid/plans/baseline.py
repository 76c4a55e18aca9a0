"""Comparators: exhaustive search, clustering without time, order only, likelihood alone, straight rescoring."""

from __future__ import annotations

import itertools

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqgrid.operators.grid import Grid
from seqgrid.plans import fit as fits
from seqgrid.plans import kernel

MAX_MODELS = 2_000_000


def set_partitions(n: int) -> np.ndarray:
    """All partitions of n items, as labels by first occurrence; Bell(n) rows."""
    rows = [[]]
    for _ in range(n):
        rows = [r + [k] for r in rows for k in range(max(r, default=-1) + 2)]
    return np.array(rows, dtype=np.int64).reshape(len(rows), n)


def exhaustive(points: DataFrame, max_models: int = MAX_MODELS, prior: str = "at_most") -> DataFrame:
    """(rank, cost, k_s, k_t, k_e, s_parts, t_parts, e_parts) of the ten best of all grids; refuses more than max_models.

    Partitions of S are dealt over tasks, each of which meets all of T and E.
    """
    rows = points.toPandas()  # bounded by the refusal below
    if rows["s"].nunique() > 9 or rows["e"].nunique() > 9 or rows["t"].nunique() > 16:
        raise ValueError("too many values for an exhaustive search")
    d, *_ = fits.data_of(rows, prior)
    s_all, e_all = set_partitions(d.ns), set_partitions(d.ne)
    models = len(s_all) * len(e_all) * 2 ** (d.nt - 1)
    if models > max_models:
        raise ValueError(f"{models} grids, more than {max_models}")

    def task(batches):  # noqa: ANN001, ANN202
        times = [np.cumsum(np.concatenate([[0], np.array(bits, np.int64)])) for bits in itertools.product((0, 1), repeat=d.nt - 1)]
        for pdf in batches:
            out = []
            for i in pdf["id"]:
                for e in e_all:
                    for t in times:
                        p = kernel.Parts(s_all[i], t, e)
                        out.append((kernel.total(d, p), int(s_all[i].max()) + 1, int(t.max()) + 1, int(e.max()) + 1, s_all[i].tolist(), t.tolist(), e.tolist()))
                out = sorted(out)[:10]
            yield pd.DataFrame(out, columns=["cost", "k_s", "k_t", "k_e", "s_parts", "t_parts", "e_parts"])

    got = points.sparkSession.range(len(s_all)).repartition(min(8, len(s_all))).mapInPandas(task, "cost double, k_s int, k_t int, k_e int, s_parts array<int>, t_parts array<int>, e_parts array<int>")
    top = got.orderBy("cost", "k_s", "k_t", "k_e").limit(10)
    return top.withColumn("rank", F.row_number().over(Window.orderBy("cost", "k_s", "k_t", "k_e")))


def no_time(points: DataFrame) -> DataFrame:
    """Points with all times one: the fit then is a two-way clustering."""
    return points.groupBy("s", "e").agg(F.sum("n").cast("long").alias("n")).select("s", F.lit(0).cast("long").alias("t"), "e", "n")


def ordinal_time(points: DataFrame) -> DataFrame:
    """Time replaced by the position within the sequence; equal times by order of the event."""
    w = Window.partitionBy("s").orderBy("t", "e").rowsBetween(Window.unboundedPreceding, 0)
    return points.select("s", (F.sum("n").over(w) - F.col("n")).cast("long").alias("t"), "e", "n")


def likelihood_path(points: DataFrame) -> DataFrame:
    """Merges that lower the likelihood alone, from the finest grid: none, which shows the need of the prior."""
    return fits.greedy(points, start="finest", objective="likelihood")


def fit_no_time(points: DataFrame, **options) -> Grid:  # noqa: ANN003
    return fits.fit(no_time(points), **options)


def fit_ordinal(points: DataFrame, **options) -> Grid:  # noqa: ANN003
    return fits.fit(ordinal_time(points), **options)
