"""Points (s, t, e, n): any table, file, nested form or token stream folded into weighted triples."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _col(x: str | Column) -> Column:
    return F.col(x) if isinstance(x, str) else x


def bind(df: DataFrame, seq: str | Column, time: str | Column, event: str | Column, weight: str | Column | None = None) -> DataFrame:
    """Just the named columns, as s, t, e, n; so scans are pruned to them and other columns can't clash."""
    n = F.lit(1).cast("long") if weight is None else _col(weight).cast("long")
    return df.select(_col(seq).alias("s"), _col(time).alias("t"), _col(event).alias("e"), n.alias("n"))


def fold(bound: DataFrame) -> DataFrame:
    """Equal triples become one row with their number: one shuffle, combined on the map side. Nulls, and weights below 1, are dropped."""
    ok = bound.where("s is not null and t is not null and e is not null and n > 0")
    return ok.groupBy("s", "t", "e").agg(F.sum("n").cast("long").alias("n"))


def from_table(df: DataFrame, seq: str | Column, time: str | Column, event: str | Column, weight: str | Column | None = None) -> DataFrame:
    return fold(bind(df, seq, time, event, weight))


def dropped_points(df: DataFrame, seq: str | Column, time: str | Column, event: str | Column) -> DataFrame:
    """One row (dropped_points): rows without a sequence, time or event."""
    b = bind(df, seq, time, event)
    return b.agg(F.coalesce(F.sum(F.when(F.col("s").isNull() | F.col("t").isNull() | F.col("e").isNull(), 1).otherwise(0)), F.lit(0)).cast("long").alias("dropped_points"))


def from_nested(df: DataFrame, seq: str, obs: str) -> DataFrame:
    """From one row a sequence with ARRAY<STRUCT<t, e>>."""
    return from_table(df.select(F.col(seq).alias("_s"), F.inline(obs)), "_s", "t", "e")


def to_nested(points: DataFrame) -> DataFrame:
    """(s, obs): observations in order of time, repeated as often as they count."""
    return points.select("s", F.explode(F.array_repeat(F.struct("t", "e"), F.col("n").cast("int"))).alias("o")).groupBy("s").agg(F.array_sort(F.collect_list("o")).alias("obs"))


def from_rows(spark: SparkSession, rows: Iterable[tuple], schema: str = "s int, t int, e string") -> DataFrame:
    return from_table(spark.createDataFrame(list(rows), schema), "s", "t", "e")


def read(spark: SparkSession, fmt: str, path: str, seq: str, time: str, event: str, schema: str | None = None, weight: str | None = None, **options: str) -> DataFrame:
    """Points of a parquet, orc, csv or json file, or of a catalog table (fmt 'table')."""
    if fmt == "table":
        return from_table(spark.table(path), seq, time, event, weight)
    reader = spark.read.format(fmt).options(**({"header": "true"} | options if fmt == "csv" else options))
    return from_table((reader.schema(schema) if schema else reader).load(path), seq, time, event, weight)


def filter(points: DataFrame, t_lo=None, t_hi=None, events: list | None = None) -> DataFrame:  # noqa: A001, ANN001
    if t_lo is not None:
        points = points.where(F.col("t") >= F.lit(t_lo))
    if t_hi is not None:
        points = points.where(F.col("t") <= F.lit(t_hi))
    return points.where(F.col("e").isin(events)) if events is not None else points


def scramble(id_col: Column) -> Column:
    """A multiplier large enough to wrap within a dozen ids: a small one would leave the order of time as it is."""
    return F.pmod(F.pmod(id_col, F.lit(2147483647)) * 182605794, F.lit(2147483647))


def subset(df: DataFrame, id_col: str, n: int) -> DataFrame:
    """n rows, nested for growing n and spread over all ids: the first by a scrambled id (a distributed top-n)."""
    return df.orderBy(scramble(F.col(id_col)), id_col).limit(n)


def min_length(points: DataFrame, m: int) -> DataFrame:
    long_enough = points.groupBy("s").agg(F.sum("n").alias("len")).where(F.col("len") >= m).select("s")
    return points.join(long_enough, "s", "left_semi")


def sample_sequences(points: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Whole sequences, by a hash of their id: no shuffle."""
    return points.where(F.pmod(F.xxhash64(F.col("s"), F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000))


def having_event(points: DataFrame, event, absent: bool = False) -> DataFrame:  # noqa: ANN001
    """Points of the sequences with (or without) an event."""
    with_it = points.where(F.col("e") == F.lit(event)).select("s").distinct()
    return points.join(with_it, "s", "left_anti" if absent else "left_semi")


def profile(points: DataFrame, approx: bool = False) -> DataFrame:
    """One row: sequences, distinct times, events, points, mean points a sequence."""
    d = F.approx_count_distinct if approx else F.countDistinct
    total = F.coalesce(F.sum("n"), F.lit(0)).cast("long")
    return points.agg(d("s").alias("n_sequences"), d("t").alias("n_times"), d("e").alias("n_events"), total.alias("n_points"), (total / F.greatest(d("s"), F.lit(1))).alias("mean_points"))


def dictionary(points: DataFrame, column: str) -> DataFrame:
    """(id, value, n): dense ids in the order of the values."""
    from seqgrid.functions.encode import ordered_ids

    return ordered_ids(points.groupBy(F.col(column).alias("value")).agg(F.sum("n").cast("long").alias("n")), "value")


def tokens(docs: DataFrame, id_col: str, text_col: str, top_k: int = 100) -> DataFrame:
    """Points (document, 1-based word position, word) of the top_k most frequent words of letters."""
    words = docs.select(F.col(id_col).alias("s"), F.posexplode(F.split(F.lower(F.trim(F.regexp_replace(text_col, r"\s+", " "))), " ")).alias("p", "e")).select("s", (F.col("p") + 1).cast("long").alias("t"), "e").where(F.col("e").rlike("^[a-zß-ÿ]+$"))
    common = words.groupBy("e").count().orderBy(F.col("count").desc(), "e").limit(top_k).select("e")
    return from_table(words.join(F.broadcast(common), "e", "left_semi"), "s", "t", "e")
