"""Change of the cost for every merge of two parts, and the merging itself.

The change is a sum of three levels, so nothing is rescored: a step of the variable level, the same for all pairs of a
dimension; the parts' own terms; and the cells present in both parts, found by a self-join of the sparse cells on
the two other coordinates. Pairs without a common cell have no cell term and come in by an outer join.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqgrid.functions.mathx import ln_fact, ln_gamma_step, variable_level
from seqgrid.operators.grid import DIMS, Grid, of_columns


def variable_step(g: Grid, dim: str, m: int = 1) -> float:
    """Change of the variable level when m merges happen in a dimension."""
    h = g.shape()
    k = {"S": h.kS, "T": h.kT, "E": h.kE}
    before = variable_level(h.n, h.a, h.N, k["S"], k["T"], k["E"], g.prior)
    k[dim] -= m
    return variable_level(h.n, h.a, h.N, k["S"], k["T"], k["E"], g.prior) - before


def part_term(dim: str, n_points: Column, n_values: Column) -> Column:
    return ln_fact(n_points) if dim == "T" else ln_gamma_step(n_values, n_points)


def pairs(g: Grid, dim: str) -> DataFrame:
    """Candidates (left, right, both sides' sizes): all unordered pairs of clusters, or neighbouring intervals."""
    p = g.parts(dim)
    l, r = p.toDF("left", "ln", "lm"), p.toDF("right", "rn", "rm")
    if dim == "T":
        return l.join(r, F.col("right") == F.col("left") + 1)
    return l.join(r, F.col("left") < F.col("right"))


def deltas(g: Grid, dim: str) -> DataFrame:
    """(dim, left, right, delta) of every candidate merge."""
    own = DIMS[dim]
    rest = [c for c in DIMS.values() if c != own]
    l = g.cells.select(*rest, F.col(own).alias("left"), F.col("n").alias("x"))
    r = g.cells.select(*rest, F.col(own).alias("right"), F.col("n").alias("y"))
    shared = l.join(r, rest).where(F.col("right") == F.col("left") + 1 if dim == "T" else F.col("left") < F.col("right"))
    both = shared.groupBy("left", "right").agg(F.sum(ln_fact(F.col("x")) + ln_fact(F.col("y")) - ln_fact(F.col("x") + F.col("y"))).alias("cell"))
    level = part_term(dim, F.col("ln") + F.col("rn"), F.col("lm") + F.col("rm")) - part_term(dim, F.col("ln"), F.col("lm")) - part_term(dim, F.col("rn"), F.col("rm"))
    step = variable_step(g, dim)
    return pairs(g, dim).join(both, ["left", "right"], "left").select(F.lit(dim).alias("dim"), "left", "right", (F.lit(step) + level + F.coalesce("cell", F.lit(0.0))).alias("delta"))


def all_deltas(g: Grid) -> DataFrame:
    return deltas(g, "S").unionByName(deltas(g, "T")).unionByName(deltas(g, "E"))


def best(g: Grid) -> DataFrame:
    """The merge of least change; ties go to S before T before E, then to lower parts."""
    rank = F.when(F.col("dim") == "S", 0).when(F.col("dim") == "T", 1).otherwise(2)
    return all_deltas(g).orderBy("delta", rank, "left", "right").limit(1)


def apply(g: Grid, merges: dict[str, dict[int, int]]) -> Grid:
    """Relabel parts: for each dimension {part: new part}; parts that aren't named keep their number. The maps are no longer than a grid's parts."""
    laid = g.laid
    for dim, relabel in merges.items():
        if relabel:
            c = DIMS[dim]
            m = laid.sparkSession.createDataFrame([(int(a), int(b)) for a, b in relabel.items()], f"{c} int, _to int")
            laid = laid.join(F.broadcast(m), c, "left").withColumn(c, F.coalesce("_to", c)).drop("_to")
    return of_columns(laid, g.prior)
