"""Agreement of a partition with known labels: adjusted Rand index, recovery of cuts, detection thresholds, stability."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def contingency(pred: DataFrame, truth: DataFrame, full: bool = False) -> DataFrame:
    """(label_p, label_t, n) from (value, part) and (value, label); with full, values of one side only count under a null label."""
    p = pred.select("value", F.col("part").cast("string").alias("label_p"))
    t = truth.select("value", F.col("label").cast("string").alias("label_t"))
    return p.join(t, "value", "full" if full else "inner").groupBy("label_p", "label_t").agg(F.count(F.lit(1)).alias("n"))


def ari(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """One row (ari). 1 for equal partitions, also where both are one cluster (0/0); about 0 for unrelated ones."""
    c = contingency(pred, truth)
    two = lambda x: x * (x - 1) / 2
    cells = c.agg(F.sum(two(F.col("n"))).alias("ij"), F.sum("n").alias("n"))
    rows = c.groupBy("label_p").agg(F.sum("n").alias("x")).agg(F.sum(two(F.col("x"))).alias("i"))
    cols = c.groupBy("label_t").agg(F.sum("n").alias("x")).agg(F.sum(two(F.col("x"))).alias("j"))
    expected = F.when(F.col("n") > 1, F.col("i") * F.col("j") / two(F.col("n"))).otherwise(0.0)
    most = (F.col("i") + F.col("j")) / 2
    return cells.crossJoin(rows).crossJoin(cols).select(F.when(most == expected, 1.0).otherwise((F.col("ij") - expected) / (most - expected)).alias("ari"))


def ari_of(a: np.ndarray, b: np.ndarray) -> float:
    """The index of two label arrays, inside a task."""
    table = np.unique(np.stack([np.unique(a, return_inverse=True)[1], np.unique(b, return_inverse=True)[1]]), axis=1, return_counts=True)
    (x, y), n = table[0], table[1]
    two = lambda v: float((v * (v - 1) / 2).sum())
    ij, i, j, all_ = two(n), two(np.bincount(x, n)), two(np.bincount(y, n)), two(np.array([len(a)]))
    expected = i * j / all_ if all_ else 0.0
    most = (i + j) / 2
    return 1.0 if most == expected else (ij - expected) / (most - expected)


def cut_recovery(found: DataFrame, true: DataFrame, tolerance: float) -> DataFrame:
    """One row (precision, recall) of (cut) tables: a cut counts when the nearest one of the other table is within the tolerance."""
    f, t = found.select(F.col("cut").cast("double").alias("f")), true.select(F.col("cut").cast("double").alias("t"))
    near = lambda a, b, x, y: a.crossJoin(F.broadcast(b)).groupBy(x).agg(F.min(F.abs(F.col(x) - F.col(y))).alias("d")).agg(F.avg((F.col("d") <= tolerance).cast("double")).alias("v"))
    p, r = near(f, t, "f", "t").withColumnRenamed("v", "precision"), near(t, f, "t", "f").withColumnRenamed("v", "recall")
    return p.crossJoin(r).select(F.coalesce("precision", F.lit(0.0)).alias("precision"), F.coalesce("recall", F.lit(0.0)).alias("recall"))


def threshold(results: DataFrame) -> DataFrame:
    """(cm, eta, detected_from): the least N from which on the index is 1 in every larger run; null if it never is."""
    w = Window.partitionBy("cm", "eta").orderBy(F.col("N").desc()).rowsBetween(Window.unboundedPreceding, 0)
    good = results.withColumn("held", F.min(F.when(F.col("ari") >= 1 - 1e-9, 1).otherwise(0)).over(w))
    return good.groupBy("cm", "eta").agg(F.min(F.when(F.col("held") == 1, F.col("N"))).alias("detected_from"))


def discovery(results: DataFrame) -> DataFrame:
    """(cm, eta, events_from, times_from, sequences_from): the least N from which on the clusters of events, all bounds, and the clusters of sequences are found in every larger run."""
    w = Window.partitionBy("cm", "eta").orderBy(F.col("N").desc()).rowsBetween(Window.unboundedPreceding, 0)
    held = lambda good: F.min(F.when(good, 1).otherwise(0)).over(w)
    one = results.withColumns({"fe": held(F.col("ari_e") >= 1 - 1e-9), "ft": held(F.col("recall") >= 1 - 1e-9), "fs": held(F.col("ari") >= 1 - 1e-9)})
    first = lambda c, name: F.min(F.when(F.col(c) == 1, F.col("N"))).alias(name)
    return one.groupBy("cm", "eta").agg(first("fe", "events_from"), first("ft", "times_from"), first("fs", "sequences_from"))


def stability(results: DataFrame) -> DataFrame:
    """(cm, eta, k_s, k_t, k_e, runs): how the numbers of parts of the runs with index 1 spread; growth with N would be over-fitting."""
    ok = results.where("ari >= 1 - 1e-9")
    spread = lambda c: F.struct(F.min(c).alias("least"), F.max(c).alias("most")).alias(c)
    return ok.groupBy("cm", "eta").agg(spread("k_s"), spread("k_t"), spread("k_e"), F.count(F.lit(1)).alias("runs"))
