"""Streams replayed day by day against the batch answers."""

from __future__ import annotations

from pyspark.sql import functions as F

from seqgrid.operators import grid
from seqgrid.sources import workloads
from seqgrid.streaming import stream


def replay(spark, sf, tmp_path, late: bool = False):
    src = workloads.load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    day = F.date_trunc("day", "ts")
    if late:
        day = F.when(F.col("event_id") % 20 == 0, F.date_add(day.cast("date"), 1).cast("timestamp")).otherwise(day)
    for i, (d,) in enumerate(src.select(day.alias("d")).distinct().orderBy("d").limit(6).collect()):
        src.where(day == F.lit(d)).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    schema = src.schema
    return spark.read.schema(schema).parquet(str(tmp_path / "in")), spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))


def run(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()
    return df.sparkSession.table(name)


def test_windows_and_duplicates(spark, sf, tmp_path):
    batch, live = replay(spark, sf, tmp_path, late=True)
    p = stream.points(live, "user_id", "ts", "event_type", "2 days")
    got = {tuple(r) for r in run(stream.window_counts(p, "1 day").select("start", "e", "n"), "w", "complete").collect()}
    b = batch.select(F.col("user_id").alias("s"), "ts", F.col("event_type").alias("e"))
    assert got == {tuple(r) for r in stream.window_counts(b, "1 day").select("start", "e", "n").collect()}
    assert run(stream.dedup(p, ["s", "ts", "e"]), "d").count() == b.distinct().count()


def test_fold_and_drift(spark, sf, tmp_path):
    batch, live = replay(spark, sf, tmp_path)
    g = workloads.fixed_grid(spark, sf)
    p = stream.points(live, "user_id", "ts", "event_type")
    q = stream.fold(p, g, str(tmp_path / "cells"), str(tmp_path / "ck")).start()
    q.processAllAvailable()
    q.stop()
    b = batch.select(F.col("user_id").alias("s"), "ts", F.col("event_type").alias("e"))
    now = stream.folded(spark, str(tmp_path / "cells"))
    assert {tuple(r) for r in now.collect()} == {tuple(r) for r in stream.cells_of(b, g).collect()}
    assert stream.drift(g, now).first()["n"] == b.count()


def test_nearest_part():
    own = {(0, 0): 5, (1, 1): 5}
    table = {0: {(0, 0): 50, (1, 1): 50}, 1: {(0, 1): 50, (1, 0): 50}}
    assert stream.nearest_part(own, table, {0: (100, 4), 1: (100, 4)}) == 0
    assert grid.DIMS["S"] == "s_part"


def test_live_assignment(spark, sf, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        batch, live = replay(spark, sf, tmp_path)
        g = workloads.fixed_grid(spark, sf)
        got = run(stream.assign(stream.points(live, "user_id", "ts", "event_type"), g), "a", "update").toPandas()
        want = batch.groupBy(F.col("user_id").alias("s")).count().toPandas()
        last = got.sort_values("n").groupby("s").last()
        assert set(last.index) == set(want.s) and set(last.part) <= {0, 1, 2, 3}
        assert (last.n <= want.set_index("s")["count"][last.index]).all()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
