"""The experiment workloads over the given tables: planted patterns, natural sequences, the star join, fixed grids."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.functions import encode
from seqgrid.functions.encode import time_key
from seqgrid.operators import grid
from seqgrid.operators.grid import Grid
from seqgrid.sources import points

MONTH = 2_592_000_000_000
START = 1_704_067_200_000_000
CUTS = ((250, 500, 750), (100, 400, 600))
TRUE_CUTS = (100, 250, 400, 500, 600, 750)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def draws(row_id: Column) -> tuple[Column, Column]:
    """Two reproducible pseudo-random whole numbers of a row id, the same in any SQL engine."""
    x1 = F.floor(F.pmod(row_id * 1103515245 + 12345, F.lit(2147483648)) / 256)
    x2 = F.floor(F.pmod((row_id + 7919) * 69069 + 1, F.lit(4294967296)) / 256)
    return x1.cast("long"), x2.cast("long")


def _plant(df: DataFrame, group: Column, eta: float | Column) -> DataFrame:
    x1, x2 = draws(F.col("id"))
    noisy = x1 % 1000 < (F.round(eta * 1000) if isinstance(eta, Column) else int(round(1000 * eta)))
    e = F.when(noisy, (group * 3 + 3 + x2 % 9) % 12).otherwise(group * 3 + x2 % 3)
    return df.withColumn("e", e.cast("int"))


def _carrier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, user, uo): events with time as micro-units, 0 to 1000 over 30 days when divided by MONTH."""
    ev = load(spark, sf_dir, "events").select(F.col("event_id").cast("long").alias("id"), F.col("user_id").cast("long").alias("user"), time_key(F.col("ts")).alias("us"))
    return ev.select("id", "user", ((F.col("us") - START) * 1000).alias("uo"))


def two_patterns(spark: SparkSession, sf_dir: str, eta: float = 0.0, cm: int | None = None, n: int | None = None, integer_time: bool = False) -> DataFrame:
    """Points with two planted patterns by parity of the user, on the real users and times of events."""
    df = _carrier(spark, sf_dir)
    if n is not None:
        df = points.subset(df, "id", n)
    if cm is not None:
        df = df.withColumn("user", F.col("user") % (2 * cm))
    lo = lambda cuts: sum(((F.col("uo") > c * MONTH).cast("int") for c in cuts), F.lit(0))
    even, odd = lo(CUTS[0]), 3 - lo(CUTS[1])
    df = _plant(df, F.when(F.col("user") % 2 == 0, even).otherwise(odd), eta)
    t = F.floor(F.col("uo") / MONTH).cast("long") if integer_time else F.col("uo")
    return points.from_table(df.withColumn("t", t), "user", "t", "e")


def sweep_points(spark: SparkSession, sf_dir: str, cms: tuple[int, ...], etas: tuple[float, ...], least: int = 64) -> DataFrame:
    """(cm, eta, size, s, t, e, n): the two patterns for every number of sequences and share of noise, on nested subsets whose sizes double from least up to the whole table, in one table."""
    carrier = _carrier(spark, sf_dir)
    total = carrier.count()
    sizes = []
    while least < total:
        sizes.append(least)
        least *= 2
    ranked = encode.ordered_ids(carrier.select("id", "user", "uo", F.struct(points.scramble(F.col("id")), "id").alias("key")), "key", name="rank")
    runs = spark.createDataFrame([(cm, eta) for cm in cms for eta in etas], "cm int, eta double")
    df = ranked.crossJoin(F.broadcast(runs)).withColumn("user", F.col("user") % (2 * F.col("cm")))
    lo = lambda cuts: sum(((F.col("uo") > c * MONTH).cast("int") for c in cuts), F.lit(0))
    planted = _plant(df, F.when(F.col("user") % 2 == 0, lo(CUTS[0])).otherwise(3 - lo(CUTS[1])), F.col("eta"))
    nested = planted.withColumn("size", F.explode(F.filter(F.array(*[F.lit(k) for k in [*sizes, total]]), lambda k: k > F.col("rank"))))
    return nested.groupBy("cm", "eta", "size", F.col("user").alias("s"), F.col("uo").alias("t"), "e").agg(F.count(F.lit(1)).alias("n"))


ROWS = np.dtype([("id", "<i8"), ("uo", "<i8"), ("user", "<i4")])


def packed_carrier(spark: SparkSession, sf_dir: str, modulus: int) -> DataFrame:
    """(block): the rows of the carrier as bytes, user modulo modulus, some thousand to a block; rows with a null are left out, as from all points."""

    def pack(batches):  # noqa: ANN001, ANN202
        for pdf in batches:
            a = np.empty(len(pdf), ROWS)
            for c in ROWS.names:
                a[c] = pdf[c].to_numpy()
            yield pd.DataFrame({"block": [a.tobytes()]})

    rows = _carrier(spark, sf_dir).where("id is not null and user is not null and uo is not null")
    return rows.select("id", "uo", (F.col("user") % modulus).alias("user")).mapInPandas(pack, "block binary")


def unpacked(blocks: list[bytes]) -> np.ndarray:
    """The rows of packed blocks, in the order in which nested subsets take them."""
    a = np.frombuffer(b"".join(blocks), ROWS)
    far = np.int64(2147483647)
    return a[np.lexsort((a["id"], a["id"] % far * 182605794 % far))]


def planted_rows(a: np.ndarray, cm: int, eta: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(s, t, e, n): what two_patterns gives for the rows a, inside a task."""
    s, t = np.fmod(a["user"], 2 * cm).astype(np.int64), a["uo"]
    x1 = (a["id"] * 1103515245 + 12345) % 2147483648 // 256
    x2 = ((a["id"] + 7919) * 69069 + 1) % 4294967296 // 256
    lo = lambda cuts: np.searchsorted(np.array(cuts, np.int64) * MONTH, t, side="left")
    group = np.where(s % 2 == 0, lo(CUTS[0]), 3 - lo(CUTS[1]))
    e = np.where(x1 % 1000 < round(eta * 1000), (group * 3 + 3 + x2 % 9) % 12, group * 3 + x2 % 3)
    order = np.lexsort((e, t, s))
    s, t, e = s[order], t[order], e[order]
    first = np.flatnonzero(np.concatenate([[True], (s[1:] != s[:-1]) | (t[1:] != t[:-1]) | (e[1:] != e[:-1])]))
    return s[first], t[first], e[first], np.diff(np.append(first, len(s)))


def many_patterns(spark: SparkSession, sf_dir: str, patterns: int = 5, eta: float = 0.0, cm: int | None = 10) -> DataFrame:
    """patterns rotations of the four event groups with shifted cuts, by user modulo patterns."""
    df = _carrier(spark, sf_dir)
    if cm is not None:
        df = df.withColumn("user", F.col("user") % (patterns * cm))
    p = F.col("user") % patterns
    t = F.pmod(F.col("uo") + p * 100 * F.lit(MONTH), F.lit(1000 * MONTH))
    return points.from_table(_plant(df, (F.floor(t / (250 * MONTH)) + p) % 4, eta), "user", "uo", "e")


def lineitem_patterns(spark: SparkSession, sf_dir: str, eta: float = 0.0, cm: int = 100, n: int | None = None) -> DataFrame:
    """The two patterns on the rows and days of lineitem: naturally discrete time and more rows."""
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-02"))
    key = (F.col("l_orderkey") * 7919 + F.col("l_partkey") * 104729 + F.col("l_suppkey") * 1299709 + F.col("l_linenumber") * 15485863).cast("long")
    df = load(spark, sf_dir, "lineitem").select(F.pmod(key, F.lit(2147483648)).alias("id"), (F.col("l_suppkey") % (2 * cm)).cast("long").alias("user"), (day.cast("long") * 1000).alias("d"))
    if n is not None:
        df = points.subset(df, "id", n)
    lo = lambda cuts: sum(((F.col("d") > c * 2498).cast("int") for c in cuts), F.lit(0))
    df = _plant(df, F.when(F.col("user") % 2 == 0, lo(CUTS[0])).otherwise(3 - lo(CUTS[1])), eta)
    return points.from_table(df.withColumn("t", F.floor(F.col("d") / 1000).cast("long")), "user", "t", "e")


def truth_of_users(p: DataFrame, patterns: int = 2) -> DataFrame:
    return p.select(F.col("s").alias("value")).distinct().withColumn("label", F.col("value") % patterns)


def truth_grid(p: DataFrame, scale: int = MONTH, split: bool = True) -> Grid:
    """The planted partitions: parity, seven intervals, four event groups."""
    t = sum(((F.col("t") > c * scale).cast("int") for c in TRUE_CUTS), F.lit(0))
    return grid.lay(p, F.col("s") % 2 if split else F.lit(0), t, F.floor(F.col("e") / 3))


def raw_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = load(spark, sf_dir, "events")
    return points.from_table(ev, "user_id", time_key(F.col("ts")), "event_type")


def fixed_grid(spark: SparkSession, sf_dir: str, planted: bool = False, eta: float = 0.2) -> Grid:
    """A grid by fixed rules, for exact comparison in SQL: user modulo 4, intervals of five days, event groups."""
    p = two_patterns(spark, sf_dir, eta) if planted else raw_events(spark, sf_dir)
    day = F.floor(F.col("t") / (86_400_000_000 * 1000)) if planted else F.floor((F.col("t") - START) / 86_400_000_000)
    e = F.floor(F.col("e") / 3) if planted else F.when(F.col("e").isin("click", "view"), 0).when(F.col("e") == "error", 1).otherwise(2)
    return grid.lay(p, F.col("s") % 4, F.floor(day / 5), e)


def by_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points.from_table(load(spark, sf_dir, "events"), "user_id", time_key(F.col("ts"), "hour_of_day"), "event_type")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points.from_table(load(spark, sf_dir, "conversations"), "conv_id", "turn", "role")


def documents(spark: SparkSession, sf_dir: str, top_k: int = 100) -> DataFrame:
    return points.tokens(load(spark, sf_dir, "documents"), "doc_id", "text", top_k)


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points.from_table(load(spark, sf_dir, "orders"), "o_custkey", time_key(F.col("o_orderdate"), "day"), "o_orderpriority")


def lineitem_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points.from_table(load(spark, sf_dir, "lineitem"), "l_suppkey", time_key(F.col("l_shipdate"), "day"), F.concat("l_returnflag", "l_linestatus"))


def star_points(spark: SparkSession, sf_dir: str, event: str = "p_type") -> DataFrame:
    """(customer, order day, part attribute) from four tables; Spark picks broadcast or sort-merge by size."""
    c = load(spark, sf_dir, "customer").select("c_custkey")
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    p = load(spark, sf_dir, "part").select("p_partkey", event)
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(p, li.l_partkey == p.p_partkey)
    return points.from_table(j, "c_custkey", time_key(F.col("o_orderdate"), "day"), event)


def toy(spark: SparkSession, repeats: int = 1) -> DataFrame:
    """Four sequences that swap two pairs of events at half time; 16 or 32 points."""
    times = ((10, 20), (60, 70)) if repeats == 1 else ((10, 20, 30, 40), (60, 70, 80, 90))
    rows = [(s, t, ("AB" if (half == 0) == (s < 2) else "CD")[i % 2]) for s in range(4) for half in (0, 1) for i, t in enumerate(times[half])]
    return points.from_rows(spark, rows)
