"""Improving one axis of a grid while the others stay: moves of single values, shifts of interval bounds."""

from __future__ import annotations

import warnings

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqgrid.functions.encode import interval_of, lookup_interval
from seqgrid.functions.mathx import ln_fact, ln_gamma_step
from seqgrid.operators.grid import DIMS, VALUE, Grid, of_columns, of_profile
from seqgrid.operators.grid import profile as fold
from seqgrid.operators.merge import variable_step


def move_deltas(g: Grid, dim: str) -> DataFrame:
    """(value, n, part, target, delta): change of cost when a value leaves its cluster for another one.

    A value's profile over the two other coordinates meets the cells of its own cluster and of every target by
    equi joins; empty target cells give the same base for all targets. The last value of a cluster takes the
    cluster with it: then the change is that of the merge.
    """
    own, v = DIMS[dim], VALUE[dim]
    rest = [c for c in DIMS.values() if c != own]
    profile = (fold(g.laid) if g.base is None else g.base).groupBy(F.col(v).alias("value"), F.col(own).alias("part"), *rest).agg(F.sum("n").cast("long").alias("x"))
    cells = g.cells.select(*rest, F.col(own).alias("target"), F.col("n").alias("y"))
    home = cells.withColumnRenamed("target", "part")
    # leaving: the own cells lose x; arriving in an empty cell: it gets x
    base = profile.join(home, [*rest, "part"]).groupBy("value", "part").agg(F.sum("x").alias("n"), F.sum(ln_fact(F.col("y")) - ln_fact(F.col("y") - F.col("x")) - ln_fact(F.col("x"))).alias("base"))
    hit = profile.join(cells, rest).where("target <> part").groupBy("value", "target").agg(F.sum(ln_fact(F.col("x")) + ln_fact(F.col("y")) - ln_fact(F.col("x") + F.col("y"))).alias("hit"))
    p = g.parts(dim)
    a, b = p.toDF("part", "an", "am"), p.toDF("target", "bn", "bm")
    gain = lambda n, m: ln_gamma_step(m, n)
    lone = F.col("am") == 1
    left = F.when(lone, 0.0).otherwise(gain(F.col("an") - F.col("n"), F.greatest(F.col("am") - 1, F.lit(1))))
    level = left - gain(F.col("an"), F.col("am")) + gain(F.col("bn") + F.col("n"), F.col("bm") + 1) - gain(F.col("bn"), F.col("bm"))
    step = F.when(lone, F.lit(variable_step(g, dim) if getattr(g.shape(), "kS" if dim == "S" else "kE") > 1 else 0.0)).otherwise(0.0)
    every = base.join(F.broadcast(a), "part").join(F.broadcast(b), F.col("target") != F.col("part"))
    return every.join(hit, ["value", "target"], "left").select("value", "n", "part", "target", (step + level + F.col("base") + F.coalesce("hit", F.lit(0.0))).alias("delta"))


def _relabelled(df: DataFrame, dim: str, to: DataFrame) -> DataFrame:
    """df with the part of the values in to (value, to) replaced."""
    own, v = DIMS[dim], VALUE[dim]
    names = to.select(F.col("value").alias(v), F.col("to").cast("int").alias("_to"))
    return df.join(names, v, "left").withColumn(own, F.coalesce("_to", own)).drop("_to")


def move_values(g: Grid, dim: str, tolerance: float = 1e-9) -> tuple[Grid, int]:
    """Moves of values to the best other cluster, pass after pass until none lowers the cost.

    All values move at once; as moves share cells, a pass is kept only if the cost fell, else the more gainful half of
    it is tried, down to the one best move, whose change is exact. Moves stay a table; a pass works on the profile,
    which lies in the shared folder, and the points are labelled once at the end.
    """
    from seqgrid.operators.score import cost
    from seqgrid.sources.persist import cut

    start = g.values(dim).select("value", F.col("part").alias("was"))
    base = cut(fold(g.laid) if g.base is None else g.base)
    g = of_profile(base, g.laid, g.prior, g.cuts)
    moved, now = 0, cost(g)
    while True:
        best = cut(move_deltas(g, dim).groupBy("value").agg(F.min_by("target", F.struct("delta", "target")).alias("to"), F.min("delta").alias("delta")).where(F.col("delta") < -tolerance))
        size = best.count()
        picks, share, many = best, 1.0, size
        while many:
            trial = of_profile(cut(_relabelled(base, dim, picks)), g.laid, g.prior, g.cuts)
            then = cost(trial)
            if then < now - tolerance:
                g, base, now, moved = trial, trial.base, then, moved + many
                break
            share /= 2
            before = many
            picks = best.where(F.col("delta") <= best.approxQuantile("delta", [share], 0.01)[0])
            many = picks.count()
            if many >= before and before > 1:
                picks, many = best.orderBy("delta", "value").limit(1), 1
            elif before == 1:
                many = 0
        if not many:
            break
    if not moved:
        return g, 0
    # back on the points, by the values whose part is another one now
    to = cut(g.values(dim).join(start, "value").where("part <> was").select("value", F.col("part").alias("to")))
    return of_profile(base, cut(_relabelled(g.laid, dim, to)), g.prior, g.cuts), moved


def _positions(g: Grid, left: Column) -> DataFrame:
    """(left, t, t_part, nl, na, c): for every distinct time of a stretch of points, by number left (an array column: the stretches a row belongs to), the cost of cutting the stretch behind it, up to a constant of the stretch: 0 for the cells uncut.

    Points are range-partitioned by time. Running counts in each cell, local to a partition plus what the partitions
    before it hold (a row for each partition and cell), give every position's cost, however long a stretch is.
    """
    from seqgrid.functions.encode import _ranged

    pt = g.laid.groupBy("t_part", "t", "s_part", "e_part").agg(F.sum("n").cast("long").alias("n"))
    two = _ranged(pt, "t").withColumn("left", F.explode(left))
    cell = ["left", "s_part", "e_part"]
    by_part = two.groupBy(*cell, "_p").agg(F.sum("n").alias("m"))
    order = Window.partitionBy(*cell).orderBy("_p")
    before = by_part.select(*cell, "_p", (F.sum("m").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("m")).alias("before"), F.sum("m").over(Window.partitionBy(*cell)).alias("all"))
    w = Window.partitionBy(*cell, "_p").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    run = two.join(before, [*cell, "_p"]).withColumn("upto", F.col("before") + F.sum("n").over(w))
    # cell terms of splitting a cell's points behind this time, relative to none before: telescoped
    f = lambda x: ln_fact(x)
    step = -(f(F.col("upto")) - f(F.col("upto") - F.col("n"))) - (f(F.col("all") - F.col("upto")) - f(F.col("all") - F.col("upto") + F.col("n")))
    by = run.groupBy("left", "_p", "t").agg(F.sum(step).alias("d"), F.sum("n").alias("n"), F.max("t_part").alias("t_part"))
    ends = by.groupBy("left", "_p").agg(F.sum("d").alias("pd"), F.sum("n").alias("pn"))
    upto = Window.partitionBy("left").orderBy("_p").rowsBetween(Window.unboundedPreceding, 0)
    ends = ends.select("left", "_p", (F.sum("pd").over(upto) - F.col("pd")).alias("bd"), (F.sum("pn").over(upto) - F.col("pn")).alias("bn"), F.sum("pn").over(Window.partitionBy("left")).alias("na"))
    o = Window.partitionBy("left", "_p").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    pos = by.join(ends, ["left", "_p"]).withColumn("nl", F.col("bn") + F.sum("n").over(o))
    return pos.select("left", "t", "t_part", "nl", "na", (F.col("bd") + F.sum("d").over(o) + f(F.col("nl")) + f(F.col("na") - F.col("nl"))).alias("c"))


def boundary_deltas(g: Grid) -> DataFrame:
    """(left, t, delta): change of cost when the bound between intervals left and left + 1 moves to behind the distinct time t."""
    last = g.shape().kT - 1
    part = F.col("t_part")
    pairs = F.filter(F.array(part - 1, part), lambda k: (k >= 0) & (k < last))
    pos = _positions(g, pairs)
    now = pos.where("t_part = left").groupBy("left").agg(F.max_by("c", "t").alias("c0"))  # a row for each bound
    return pos.where("nl < na").join(now, "left").select("left", "t", (F.col("c") - F.col("c0")).alias("delta"))


def split_deltas(g: Grid) -> DataFrame:
    """(t_part, t, delta): change of the part and cell levels when an interval is cut behind the distinct time t; the step of the variable level comes on top."""
    pos = _positions(g, F.array("t_part")).where("nl < na")
    return pos.select("t_part", "t", (F.col("c") - ln_fact(F.col("na"))).alias("delta"))


def _labelled(g: Grid, cuts: list) -> Grid:
    part = interval_of(F.col("t"), cuts) if len(cuts) <= 32 else lookup_interval(F.col("t"), cuts)
    return of_columns(g.laid.withColumn("t_part", part), g.prior, cuts)


def move_bounds(g: Grid, tolerance: float = 1e-9) -> tuple[Grid, int]:
    """Shifts of bounds to their best place until none lowers the cost, even and odd bounds in turn so that shifts of one pass are independent.

    Bounds are as many as the grid's intervals, and go over the driver; the points are labelled anew from their list.
    """
    moved = quiet = turn = 0
    cuts = [r["t_hi"] for r in g.t_parts.orderBy("t_part").collect()][:-1]
    while cuts and quiet < 2:
        todo = boundary_deltas(g).where(F.col("left") % 2 == turn % 2)
        best = todo.groupBy("left").agg(F.min_by("t", F.struct("delta", "t")).alias("t"), F.min("delta").alias("delta")).where(F.col("delta") < -tolerance).collect()
        turn += 1
        quiet = 0 if best else quiet + 1
        if best:
            for r in best:
                cuts[r["left"]] = r["t"]
            g = _labelled(g, cuts)
            moved += len(best)
    return g, moved


def split_intervals(g: Grid, tolerance: float = 1e-9) -> tuple[Grid, int]:
    """Best cuts of intervals, pass after pass until none lowers the cost: merging and shifting can't make a bound that no start had.

    Cuts of different intervals add up exactly but for the variable level, which is known for any number of them; the
    longest prefix by change that lowers the cost is made.
    """
    made = 0
    while True:
        best = split_deltas(g).groupBy("t_part").agg(F.min_by("t", F.struct("delta", "t")).alias("t"), F.min("delta").alias("delta")).orderBy("delta", "t_part").collect()
        run, least, take = 0.0, -tolerance, 0
        for m, r in enumerate(best, 1):  # a row for each interval
            run += r["delta"]
            value = run + variable_step(g, "T", -m)
            if value < least:
                least, take = value, m
        if not take:
            return g, made
        cuts = sorted([r["t_hi"] for r in g.t_parts.orderBy("t_part").collect()][:-1] + [r["t"] for r in best[:take]])
        g = _labelled(g, cuts)
        made += take


def alternate(g: Grid, order: tuple[str, ...] = ("S", "E", "T", "split"), max_rounds: int = 50) -> tuple[Grid, int]:
    """Improve one axis after the other until none moves: (grid, moves). The cost falls with every move, so it ends; a warning tells if max_rounds ended it."""
    from seqgrid.sources.persist import cut

    quiet = moved = 0
    for k in range(max_rounds * len(order)):
        dim = order[k % len(order)]
        g, m = move_bounds(g) if dim == "T" else split_intervals(g) if dim == "split" else move_values(g, dim)
        if m and dim not in VALUE:
            g = of_columns(cut(g.laid), g.prior, g.cuts)
        moved += m
        quiet = 0 if m else quiet + 1
        if quiet == len(order):
            return g, moved
    warnings.warn(f"values or bounds still move after {max_rounds} rounds", stacklevel=2)
    return g, moved
