"""Streams of points: late rows, windows, sessions, duplicates, drift of a fixed grid, live assignment."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from seqgrid.functions.encode import time_key
from seqgrid.operators.grid import Grid


def points(stream: DataFrame, seq: str, time: str, event: str, delay: str = "1 day") -> DataFrame:
    """(s, ts, e) with a watermark: rows later than the delay are dropped by what follows."""
    b = stream.select(F.col(seq).alias("s"), F.col(time).cast("timestamp").alias("ts"), F.col(event).alias("e"))
    return b.where("s is not null and ts is not null and e is not null").withWatermark("ts", delay)


def window_counts(p: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(start, end, e, n) in tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return p.groupBy(w.alias("w"), "e").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "e", "n")


def sessions(p: DataFrame, gap: str) -> DataFrame:
    """(s, start, end, n) of each sequence's sessions."""
    return p.groupBy(F.session_window("ts", gap).alias("w"), "s").agg(F.count(F.lit(1)).alias("n")).select("s", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedup(p: DataFrame, key: list[str]) -> DataFrame:
    """One row for each key within the watermark."""
    return p.dropDuplicatesWithinWatermark(key)


def cells_of(batch: DataFrame, g: Grid, unit: str = "us") -> DataFrame:
    """(s_part, t_part, e_part, n) of a batch on a fixed grid; values that the grid doesn't know have part -1.

    Interval bounds of a grid are few and broadcast; the maps of S and E join by Spark's own choice.
    """
    bounds = [r["t_hi"] for r in g.t_parts.orderBy("t_part").collect()][:-1]
    from seqgrid.functions.encode import lookup_interval

    b = batch.select("s", lookup_interval(time_key(F.col("ts"), unit), bounds).alias("t_part"), "e")
    s = g.s_values.select(F.col("value").alias("s"), F.col("part").alias("s_part"))
    e = g.e_values.select(F.col("value").alias("e"), F.col("part").alias("e_part"))
    x = b.join(s, "s", "left").join(e, "e", "left").select(F.coalesce("s_part", F.lit(-1)).alias("s_part"), "t_part", F.coalesce("e_part", F.lit(-1)).alias("e_part"))
    return x.groupBy("s_part", "t_part", "e_part").agg(F.count(F.lit(1)).alias("n"))


def fold(p: DataFrame, g: Grid, path: str, checkpoint: str, unit: str = "us"):  # noqa: ANN201
    """Start a query that writes each batch's cells under path/batch=<id>. A batch that is run again overwrites its own folder, so counts are exact."""

    def write(batch: DataFrame, batch_id: int) -> None:
        cells_of(batch, g, unit).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return p.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).outputMode("append")


def folded(spark, path: str) -> DataFrame:  # noqa: ANN001
    """Current cells of a fold."""
    return spark.read.parquet(path).groupBy("s_part", "t_part", "e_part").agg(F.sum("n").cast("long").alias("n"))


def drift(g: Grid, cells: DataFrame) -> DataFrame:
    """One row (n, grid_nats, null_nats, drifted): mean code length of new points' cells under the grid's cell shares against that of independent axes; drifted when the grid explains them no better."""
    N = float(max(g.shape().N, 1))
    k = g.shape().k
    share = g.cells.select("s_part", "t_part", "e_part", F.col("n").alias("seen"))
    axis = lambda c: g.cells.groupBy(c).agg((F.sum("n") / N).alias("p_" + c))
    x = cells.join(F.broadcast(share), ["s_part", "t_part", "e_part"], "left")
    for c in ("s_part", "t_part", "e_part"):
        x = x.join(F.broadcast(axis(c)), c, "left").fillna(1 / (N + 1), ["p_" + c])
    grid_nats = -F.log((F.coalesce("seen", F.lit(0)) + 1 / k) / (N + 1))
    null_nats = -F.log(F.col("p_s_part") * F.col("p_t_part") * F.col("p_e_part"))
    out = x.agg(F.sum("n").cast("long").alias("n"), (F.sum(F.col("n") * grid_nats) / F.sum("n")).alias("grid_nats"), (F.sum(F.col("n") * null_nats) / F.sum("n")).alias("null_nats"))
    return out.withColumn("drifted", F.col("grid_nats") >= F.col("null_nats"))


class Assigner(StatefulProcessor):
    """Keeps each sequence's counts by (interval, event cluster) and emits its nearest cluster when it changes."""

    def __init__(self, table: dict[int, dict[tuple[int, int], int]], sizes: dict[int, tuple[int, int]]):
        self.table, self.sizes = table, sizes

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.profile = handle.getMapState("profile", "t int, e int", "n long")
        self.last = handle.getValueState("last", "part int")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802, N803
        for pdf in rows:
            for (t, e), n in pdf.groupby(["t_part", "e_part"]).size().items():
                k = (int(t), int(e))
                have = self.profile.getValue(k)[0] if self.profile.containsKey(k) else 0
                self.profile.updateValue(k, (have + int(n),))
        own = {tuple(k): v[0] for k, v in self.profile.iterator()}
        part = nearest_part(own, self.table, self.sizes)
        if not self.last.exists() or self.last.get()[0] != part:
            self.last.update((part,))
            yield pd.DataFrame({"s": [key[0]], "part": [part], "n": [sum(own.values())]})

    def close(self) -> None:
        pass


def nearest_part(own: dict[tuple[int, int], int], table: dict[int, dict[tuple[int, int], int]], sizes: dict[int, tuple[int, int]]) -> int:
    from math import lgamma

    n = sum(own.values())

    def change(part: int) -> float:
        N, m = sizes[part]
        level = lgamma(N + n + m + 1) - lgamma(m + 1) - lgamma(N + m) + lgamma(m)
        return level + sum(lgamma(table[part].get(k, 0) + 1) - lgamma(table[part].get(k, 0) + x + 1) for k, x in own.items())

    return min(sorted(sizes), key=change)


def assign(p: DataFrame, g: Grid, unit: str = "us") -> DataFrame:
    """Live (s, part, n): emitted when a sequence's nearest cluster changes. The grid's cells go with the query; they are few."""
    from seqgrid.functions.encode import lookup_interval

    bounds = [r["t_hi"] for r in g.t_parts.orderBy("t_part").collect()][:-1]
    table: dict[int, dict[tuple[int, int], int]] = {}
    for r in g.cells.collect():
        table.setdefault(r["s_part"], {})[(r["t_part"], r["e_part"])] = r["n"]
    sizes = {r["part"]: (r["n_points"], r["n_values"]) for r in g.parts("S").collect()}
    e = g.e_values.select(F.col("value").alias("e"), F.col("part").alias("e_part"))
    x = p.select("s", lookup_interval(time_key(F.col("ts"), unit), bounds).alias("t_part"), "e").join(F.broadcast(e), "e").select("s", "t_part", "e_part")
    return x.groupBy("s").transformWithStateInPandas(Assigner(table, sizes), "s long, part int, n long", "Update", "None")
