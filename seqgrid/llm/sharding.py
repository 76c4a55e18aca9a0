"""Operator 10, sharding by extendible hashing.

The directory is indexed by the leading bits of a 60-bit hash of the document id (the first 15 hexadecimal
digits of its MD5, so that any SQL engine finds the same bits). A bucket holds the documents of one bit prefix;
only a bucket above the byte limit splits, on its next bit, until each one fits. So a document's shard is the
shortest prefix of its hash whose documents have at most ``limit`` bytes of text together.

Distribution: one aggregation gives bytes by prefix at a first depth of log2(total / limit) + 4 bits (about
16 cells a shard, far fewer rows than documents); the levels above it are rolled up from those cells, and only
cells that are still too large are cut deeper, in a second round over their own documents. No text
moves: the assignment needs ids and lengths only. The directory is joined by prefix, and broadcast by Spark
only below its own size threshold.

Defined results: null ids hash as the empty string; a null or empty text counts 0 bytes; rows that no bit can
separate (one document above the limit, or equal ids) share a shard of depth 60 with ``fits`` false; an empty
table gives no rows. Equal rows go to the same shard, each with its own row.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqgrid.llm.common import cut, keyed_docs, load

BITS, LIMIT = 60, 64 << 20


def hash_bits(doc_id: Column) -> Column:
    """The id's hash as a string of 60 binary digits."""
    value = F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit(""))), 1, 15), 16, 2)
    return F.lpad(value, BITS, "0")


def _levels(cells: DataFrame, low: int, high: int, limit: int) -> tuple[DataFrame, DataFrame]:
    """Of cells (prefix of length high, n_bytes, n_docs): leaves at depths low..high, and the cells that need more bits."""
    by = cells.select("n_bytes", "n_docs", F.col("prefix").alias("cell"), F.explode(F.sequence(F.lit(low), F.lit(high))).alias("depth")).withColumn("prefix", F.expr("substring(cell, 1, depth)"))
    sums = by.groupBy("depth", "prefix").agg(F.sum("n_bytes").alias("shard_bytes"), F.sum("n_docs").alias("shard_docs"))
    fit = sums.where(F.col("shard_bytes") <= limit)
    # a prefix is a leaf when it fits and the prefix one bit shorter doesn't
    over = sums.where(F.col("shard_bytes") > limit).select((F.col("depth") + 1).alias("depth"), F.col("prefix").alias("parent"))
    leaf = fit.withColumn("parent", F.expr("substring(prefix, 1, depth - 1)"))
    leaves = leaf.join(over, ["depth", "parent"], "left_semi") if low else leaf.where("depth = 0").unionByName(leaf.where("depth > 0").join(over, ["depth", "parent"], "left_semi"))
    leaves = leaves.select("depth", "prefix", "shard_bytes", "shard_docs")
    # below the first level of a round all parents are over the limit already
    if low:
        leaves = leaves.unionByName(leaf.where(F.col("depth") == low).select(*leaves.columns))
    return leaves, sums.where((F.col("depth") == high) & (F.col("shard_bytes") > limit))


def directory(sizes: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(depth, prefix, shard_bytes, shard_docs, fits) from (bits, n_bytes)."""
    total = sizes.agg(F.sum("n_bytes")).first()[0] or 0
    high = min(BITS, max(0, math.ceil(math.log2(max(total, 1) / limit))) + 4)
    low, left, parts = 0, sizes, []
    while True:
        cells = left.groupBy(F.substring("bits", 1, high).alias("prefix") if high else F.lit("").alias("prefix")).agg(F.sum("n_bytes").alias("n_bytes"), F.count(F.lit(1)).alias("n_docs"))
        leaves, deep = _levels(cut(cells), low, high, limit)
        parts.append(leaves.withColumn("fits", F.lit(True)))
        deep = cut(deep)
        if deep.isEmpty():
            break
        if high >= BITS:
            parts.append(deep.select("depth", "prefix", "shard_bytes", "shard_docs", F.lit(False).alias("fits")))
            break
        left = left.join(deep.select(F.col("prefix").alias("deep")), F.substring("bits", 1, high) == F.col("deep"), "left_semi")
        low, high = high + 1, BITS
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return cut(out)


def assign(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(doc_id, n_bytes, shard, depth, shard_bytes, shard_docs, fits); shard is the bit prefix, '' for a single shard."""
    sizes = keyed_docs(docs).select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), hash_bits(F.col("doc_id")).alias("bits"))
    leaves = directory(sizes, limit)
    depths = [r[0] for r in leaves.select("depth").distinct().orderBy("depth").collect()]  # 61 values at most
    # each document probes the directory once for each depth in use; exactly one probe finds its leaf
    probe = sizes.withColumn("depth", F.explode(F.array(*[F.lit(d) for d in depths]) if depths else F.array().cast("array<int>"))).withColumn("prefix", F.expr("substring(bits, 1, depth)"))
    return probe.join(leaves, ["depth", "prefix"]).select("doc_id", "n_bytes", F.col("prefix").alias("shard"), "depth", "shard_bytes", "shard_docs", "fits")


def write_shards(docs: DataFrame, path: str, limit: int = LIMIT) -> None:
    """The documents, in one folder and one file for each shard."""
    found = assign(docs, limit).select("doc_id", "shard").dropDuplicates(["doc_id"])
    out = docs.join(found, docs["doc_id"].eqNullSafe(found["doc_id"])).drop(found["doc_id"])
    out.repartition("shard").sortWithinPartitions("shard", "doc_id").write.mode("overwrite").partitionBy("shard").parquet(path)


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(load(spark, sf_dir, "documents"))


def sharding_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over all documents with shards of 64 KiB, so that many buckets split."""
    return assign(load(spark, sf_dir, "documents"), 64 << 10)


def oracle(limit: int, deepest: int = 60) -> str:
    return f"""
WITH d AS (SELECT doc_id, coalesce(strlen(text), 0)::BIGINT AS n_bytes,
                  ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT AS h FROM documents),
     p AS (SELECT doc_id, n_bytes, depth, h >> (60 - depth) AS cell FROM d, range(0, {deepest + 1}) r(depth)),
     s AS (SELECT depth, cell, sum(n_bytes)::BIGINT AS shard_bytes, count(*)::BIGINT AS shard_docs FROM p GROUP BY ALL),
     j AS (SELECT p.doc_id, p.n_bytes, p.depth, p.cell, s.shard_bytes, s.shard_docs,
                  row_number() OVER (PARTITION BY p.doc_id ORDER BY p.depth) AS rn
           FROM p JOIN s USING (depth, cell) WHERE s.shard_bytes <= {limit} OR depth = 60)
SELECT doc_id, n_bytes, CASE WHEN depth = 0 THEN '' ELSE right(lpad(bin(cell), 64, '0'), depth::INT) END AS shard,
       depth::INT AS depth, shard_bytes, shard_docs, shard_bytes <= {limit} AS fits
FROM j WHERE rn = 1"""
