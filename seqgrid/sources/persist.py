"""Saving and loading grids, exporting views, and cutting lineage in the folder that executors share."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.operators.grid import Grid


def cut(df: DataFrame) -> DataFrame:
    """A checkpoint in spark.checkpoint.dir; a temporary folder only where the session names none and runs on this machine alone."""
    sc = df.sparkSession.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not named and (not sc.master.startswith("local") or sc.master.startswith("local-cluster")):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="seqgrid-checkpoint-"))
    return df.checkpoint(eager=True)


def save(g: Grid, path: str) -> None:
    """cells, values of S and E, intervals and the labelled points, each a Parquet table; labelled points by interval, so that time filters prune."""
    g.cells.write.mode("overwrite").parquet(f"{path}/cells")
    g.s_values.write.mode("overwrite").parquet(f"{path}/s_values")
    g.e_values.write.mode("overwrite").parquet(f"{path}/e_values")
    g.t_parts.write.mode("overwrite").parquet(f"{path}/t_parts")
    g.laid.repartition("t_part").sortWithinPartitions("s_part", "e_part").write.mode("overwrite").partitionBy("t_part").parquet(f"{path}/laid")
    g.cells.sparkSession.range(1).select(F.lit(g.prior).alias("prior")).write.mode("overwrite").parquet(f"{path}/meta")


def load(spark: SparkSession, path: str) -> Grid:
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    laid = read("laid").select("s", "t", "e", "n", "s_part", F.col("t_part").cast("int").alias("t_part"), "e_part")
    return Grid(laid, read("cells"), read("s_values"), read("e_values"), read("t_parts"), read("meta").first()["prior"])


def export(df: DataFrame, path: str, fmt: str = "csv") -> None:
    """A view or tree in one of csv, json, parquet or orc."""
    if fmt not in ("csv", "json", "parquet", "orc"):
        raise ValueError(f"unknown format {fmt}")
    w = df.write.mode("overwrite").format(fmt)
    (w.option("header", True) if fmt == "csv" else w).save(path)
