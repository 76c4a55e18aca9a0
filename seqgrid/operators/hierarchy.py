"""Coarsening on past the optimum: merge trees, information kept, and cuts at a chosen grain."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqgrid.operators import merge
from seqgrid.operators.grid import DIMS, Grid
from seqgrid.operators.score import cost

MERGES = "step int, dim string, left int, right int, delta double, cost double, k_s int, k_t int, k_e int, info_ratio double"


def dissimilarity(g: Grid, dim: str) -> DataFrame:
    """The change of cost of a merge, read as a distance of two parts."""
    return merge.deltas(g, dim)


def info_ratio(value: Column, best: Column | float, null: Column | float) -> Column:
    """Share of the gain over the null grid that is kept; null where there was no gain."""
    best, null = (x if isinstance(x, Column) else F.lit(float(x)) for x in (best, null))
    return F.when(F.abs(best - null) > 1e-9, (value - null) / (best - null))


def build(g: Grid) -> DataFrame:
    """The merges down to one cell, over the three axes together: (step, dim, left, right, delta, cost, k_s, k_t, k_e, info_ratio).

    left < right are parts of the optimum, each standing for the group that it leads. One task: a fitted grid has
    few parts; the cells go to it, never the points.
    """
    from seqgrid.plans import kernel

    best, h, prior = cost(g), g.shape(), g.prior
    s, e = g.parts("S"), g.parts("E")
    sizes = {r["part"]: r["n_values"] for r in s.collect()}, {r["part"]: r["n_values"] for r in e.collect()}

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        code = [np.unique(pdf[c], return_inverse=True) for c in DIMS.values()]
        (sv, si), (tv, ti), (ev, ei) = code
        d = kernel.Data(si, ti, ei, pdf["n"].to_numpy(), len(sv), len(tv), len(ev), np.array([sizes[0][x] for x in sv]), np.array([sizes[1][x] for x in ev]), h.n, h.a, prior)
        p = kernel.Parts(np.arange(len(sv)), np.arange(len(tv)), np.arange(len(ev)))
        heads = [list(sv), list(tv), list(ev)]
        rows, now = [], best
        for i, (dim, left, right, delta, *k) in enumerate(kernel.merge_to_null(d, p)):
            now += delta
            a, b = heads[dim][left], heads[dim].pop(right)
            heads[dim][left] = min(a, b)
            rows.append((i, "STE"[dim], int(min(a, b)), int(max(a, b)), float(delta), float(now), *k))
        null = rows[-1][5] if rows else best
        gain = best - null
        return pd.DataFrame([(*r, (r[5] - null) / gain if abs(gain) > 1e-9 else None) for r in rows], columns=[x.split()[0] for x in MERGES.split(", ")])

    return g.cells.groupBy(F.lit(0).alias("all")).applyInPandas(task, MERGES)


def cut(g: Grid, merges: DataFrame, k_s: int | None = None, k_t: int | None = None, k_e: int | None = None, max_cells: float | None = None, min_info: float | None = None) -> Grid:
    """The grid after the shortest path at which all asked sizes hold; with min_info the longest path that keeps it.

    The path is as long as the optimum has parts, so it is replayed on the driver.
    """
    rows = merges.orderBy("step").collect()
    label = {d: {} for d in DIMS}
    h = g.shape()

    def small(ks: int, kt: int, ke: int) -> bool:
        return all(want is None or have <= want for have, want in ((ks, k_s), (kt, k_t), (ke, k_e), (float(ks) * kt * ke, max_cells)))

    upto = 0
    if min_info is not None:
        held = [i for i, r in enumerate(rows, 1) if r["info_ratio"] is not None and r["info_ratio"] >= min_info - 1e-12]
        upto = max(held, default=0)
    elif not small(h.kS, h.kT, h.kE):
        upto = next((i for i, r in enumerate(rows, 1) if small(r["k_s"], r["k_t"], r["k_e"])), len(rows))
    for r in rows[:upto]:
        m = label[r["dim"]]
        m[r["right"]] = r["left"]
    out = {}
    for dim, m in label.items():
        def root(p: int, m: dict = m) -> int:
            while p in m:
                p = m[p]
            return p

        out[dim] = {p: root(p) for p in m}
    return merge.apply(g, out)


def tree(merges: DataFrame, dim: str) -> DataFrame:
    """(node, parent, height, step): the dendrogram of one axis; a node is named part@step of its making, leaves part@-1; height is the running sum of the changes."""
    from pyspark.sql import Window

    run = merges.withColumn("height", F.sum("delta").over(Window.partitionBy(F.lit(0)).orderBy("step").rowsBetween(Window.unboundedPreceding, 0))).where(F.col("dim") == dim)
    made = run.select(F.col("left").alias("p"), F.col("step").alias("born"))
    child = run.select("step", "height", F.explode(F.array("left", "right")).alias("p"))
    last = child.join(made, "p", "left").groupBy("step", "height", "p").agg(F.coalesce(F.max(F.when(F.col("born") < F.col("step"), F.col("born"))), F.lit(-1)).alias("born"))
    parent = run.select("step", F.concat_ws("@", "left", "step").alias("parent"))
    return last.join(parent, "step").select(F.concat_ws("@", "p", "born").alias("node"), "parent", "height", "step")
