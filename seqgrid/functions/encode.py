"""Time keys, interval look-up, quantile cuts, as-of join and dense ordered ids."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MAX_LITERAL_CUTS = 256


def time_key(col: Column, unit: str = "us") -> Column:
    """An order-preserving BIGINT of a date or timestamp (microseconds, seconds, hours or days since 1970, or the hour of day)."""
    ts = col.cast("timestamp")  # timestamp_ntz has no microseconds function of its own
    us = F.unix_micros(ts)
    if unit == "hour_of_day":
        return F.hour(ts).cast("long")
    size = {"us": 1, "s": 1_000_000, "hour": 3_600_000_000, "day": 86_400_000_000}[unit]
    return us if size == 1 else F.floor(us / F.lit(size)).cast("long")


def interval_of(t: Column, cuts: Sequence[float]) -> Column:
    """Number of cuts below t: the index of its interval, intervals closed on the right."""
    if not len(cuts):
        return F.when(t.isNotNull(), F.lit(0)).cast("int")
    if len(cuts) > MAX_LITERAL_CUTS:
        raise ValueError(f"more than {MAX_LITERAL_CUTS} cuts: use join_intervals")
    marks = F.array(*[F.lit(c) for c in cuts])
    return F.size(F.filter(marks, lambda c: c < t)).cast("int")


def join_intervals(df: DataFrame, parts: DataFrame, time: str = "t") -> DataFrame:
    """Adds t_part by a range join against intervals [t_lo, t_hi]. They are at most as many as a grid has, and are broadcast."""
    return df.join(F.broadcast(parts.select("t_part", "t_lo", "t_hi")), (F.col(time) >= F.col("t_lo")) & (F.col(time) <= F.col("t_hi"))).drop("t_lo", "t_hi")


def lookup_interval(t: Column, cuts: Sequence[float]) -> Column:
    """interval_of for many cuts: a two-level search over literal arrays, O(sqrt(number of cuts)) for each row."""
    n = len(cuts)
    if n <= 32:
        return interval_of(t, cuts)
    step = int(n**0.5) + 1
    heads = F.array(*[F.lit(c) for c in cuts[::step]])
    block = F.size(F.filter(heads, lambda c: c < t)) - 1
    rows = F.array(*[F.array(*[F.lit(c) for c in cuts[i : i + step]]) for i in range(0, n, step)])
    return F.when(block < 0, F.lit(0)).otherwise(block * step + F.size(F.filter(F.get(rows, block), lambda c: c < t))).cast("int")


def quantile_cuts(points: DataFrame, k: int, exact: bool = False, column: str = "t", weight: str = "n") -> list:
    """At most k - 1 cuts into intervals of about equal frequency; equal times are never separated."""
    if k < 2:
        return []
    probs = [i / k for i in range(1, k)]
    if exact:
        by = points.groupBy(column).agg(F.sum(weight).alias("w"))
        ids = ordered_ids(by, column, "w")
        total = ids.agg(F.max("upto")).first()[0] or 0
        rows = ids.select(column, F.floor(F.col("upto") * k / F.lit(max(total, 1))).alias("q"), (F.floor((F.col("upto") - F.col("w")) * k / F.lit(max(total, 1)))).alias("p")).where("q > p and q < " + str(k)).select(column).orderBy(column)
        return [r[0] for r in rows.collect()]
    # a weight of n counts n times: rows are repeated up to 16 times, larger weights keep their share among 16
    most = points.agg(F.max(weight)).first()[0] or 1
    times = F.col(weight) if most <= 16 else F.greatest(F.lit(1), F.round(F.col(weight) * 16 / F.lit(most)))
    spread = points.select(column) if most == 1 else points.select(F.explode(F.array_repeat(F.col(column), times.cast("int"))).alias(column))
    got, top = spread.agg(F.percentile_approx(column, probs, max(10000, 20 * k)), F.max(column)).first()
    return sorted({x for x in (got or []) if x is not None and x < top})


def ordered_ids(df: DataFrame, column: str, weight: str | None = None, name: str = "id") -> DataFrame:
    """Dense ids from 0 in the order of a column (and running sums 'upto' of a weight), without a one-partition window.

    Rows are range-partitioned; the sizes of the partitions before a row's own, one number each, go over the driver.
    """
    sort = _ranged(df, column)
    w = Window.partitionBy("_p").orderBy(column)
    inner = sort.withColumn("_r", F.row_number().over(w) - 1)
    inner = inner.withColumn("_u", F.sum(weight).over(w.rowsBetween(Window.unboundedPreceding, 0))) if weight else inner
    sizes = sort.groupBy("_p").agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(weight) if weight else F.lit(0), F.lit(0)).cast("long").alias("w"))
    before, rows, mass = [], 0, 0
    for r in sorted(sizes.collect(), key=lambda r: r["_p"]):  # one row for each partition
        before.append((r["_p"], rows, mass))
        rows, mass = rows + r["n"], mass + r["w"]
    offsets = df.sparkSession.createDataFrame(before, "_p int, _o long, _ow long")
    out = inner.join(F.broadcast(offsets), "_p").withColumn(name, (F.col("_o") + F.col("_r")).cast("long"))
    if weight:
        out = out.withColumn("upto", (F.col("_ow") + F.col("_u")).cast("long"))
    return out.drop("_p", "_r", "_u", "_o", "_ow")


def _ranged(df: DataFrame, column: str) -> DataFrame:
    """Range-partitioned rows with their partition's number _p, in the shared folder: bounds come from a sample, which another run of the same plan could draw otherwise."""
    from seqgrid.sources.persist import cut

    ranged = cut(df.repartitionByRange(column).withColumn("_p", F.spark_partition_id()))
    # a checkpoint keeps its input's column ids; fresh ones let it be joined to what it came from
    return ranged.select(*[F.col(c).alias(c) for c in ranged.columns])


def asof(left: DataFrame, right: DataFrame, key: str, value: str) -> DataFrame:
    """Each left row with the latest non-null right value at or before its key.

    One range shuffle of the union; within a partition a window carries values on, and what a partition inherits is
    the last value of those before it, one row each.
    """
    both = left.select(F.col(key), F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("_side")).unionByName(right.where(F.col(value).isNotNull()).select(F.col(key), F.col(value), F.lit(0).alias("_side")))
    rows = _ranged(both, key)
    w = Window.partitionBy("_p").orderBy(key, "_side").rowsBetween(Window.unboundedPreceding, 0)
    ends = rows.groupBy("_p").agg(F.max_by(value, F.when(F.col("_side") == 0, F.col(key))).alias("_v"))
    before, last = [], None
    for r in sorted(ends.collect(), key=lambda r: r["_p"]):  # one row for each partition
        before.append((r["_p"], last))
        last = r["_v"] if r["_v"] is not None else last
    before = left.sparkSession.createDataFrame(before, f"_p int, _before {right.schema[value].dataType.simpleString()}")
    out = rows.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").join(F.broadcast(before), "_p", "left")
    return out.select(key, F.coalesce(value, "_before").alias(value))
