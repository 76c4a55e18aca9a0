"""Operator 6, n-gram Jaccard self-join through token-group matrices.

Texts become sets of hashed word trigrams (lower-cased; a text of one or two words has one shorter gram).
Every text is a query against all others; pairs with Jaccard similarity of at least ``threshold`` are found.

1. *Nodes.* Texts with equal sets are one node (fingerprint of the set); its least id represents it.
2. *Groups.* Nodes carry BANDS keys, each of ROWS minima of independent hash functions. A node's group is the
   least node among all that share a key with it: a partition of similar texts.
3. *Probes.* A node probes its own group and each further group with a member that shares one of its keys. Of
   two groups only one probes the other, so every candidate pair meets once.
4. *Matrix.* Where a group is opened, its token union is the row index of a token x member matrix in compressed
   form. The overlap of a probe with the union bounds its overlap with each member: a group opens only when that
   reaches t/(1+t) * (|query| + least member). An opened group gives all exact overlaps by one count over the
   columns of the query's tokens.

At the threshold itself a pair shares no key with probability (1 - t^ROWS)^BANDS, 1.4 % at 0.5, and far less
above it. Nothing is capped: the members of a group of more than BLOCK_TOKENS tokens, and the nodes that probe it, are
cut in blocks of which any two that have to meet do so in a task of their own, so a task holds about two blocks
whatever the size of the group; of the links it finds it keeps a forest and a number for each node. Only texts with a
candidate are read again; their ids are broadcast up to BROADCAST_IDS, else joined.

Result of classes(), which op6 returns: (doc_id, class_id, links), a row for each id. Two ids are in one class if links
lead from one to the other, and its name is its least id; links is the number of other texts with a Jaccard similarity
of at least the threshold to the document's text, copies included. An id with several texts has the sum over them (two
texts of its own that are alike are a link as well). Texts without words (null, empty) have no link; rows with null ids
are left out, repeated rows count once, and further columns are ignored.

every_pair() lists all pairs of ids, so its rows grow as the square of the groups of copies; join() has the short form:
pairs of different sets between their representatives, and one pair of each further text of an equal set with its
representative. Neither pairs an id with itself.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import byte_slices, cut, keyed_docs, load, mix, shingle_table, signed, word_table

WIDTH, BANDS, ROWS, THRESHOLD = 3, 32, 3, 0.5
BLOCK_TOKENS, BROADCAST_IDS = 1 << 18, 4 << 20
BLOCK_IDS = 1024  # texts of one side of a pair of nodes that one row expands
_RNG = np.random.default_rng(20240229)
_MUL = _RNG.integers(1, 1 << 32, BANDS * ROWS, dtype=np.uint32) | np.uint32(1)
_ADD = _RNG.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32)


def _token_sets(buf: np.ndarray, offs: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    _, _, h, doc = word_table(buf, offs)
    return shingle_table(h, doc, len(offs) - 1, width)


def _fingerprints(tokens: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """An order-free hash of each set; sets must not be empty."""
    with np.errstate(over="ignore"):
        return mix(np.add.reduceat(mix(tokens + np.uint64(0x51ED)), ptr[:-1]) + np.diff(ptr).astype(np.uint64))


def _band_keys(tokens: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    low = (tokens >> np.uint64(32)).astype(np.uint32)
    keys = np.empty((len(ptr) - 1, BANDS), np.uint64)
    with np.errstate(over="ignore"):
        for b in range(BANDS):
            key = np.full(len(ptr) - 1, b, np.uint64)
            for r in range(b * ROWS, (b + 1) * ROWS):
                x = low * _MUL[r] + _ADD[r]
                x ^= x >> np.uint32(15)
                x *= np.uint32(0x2C1B3C6D)
                key = mix(key * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat(x, ptr[:-1]))
            keys[:, b] = key
    return keys


def signatures(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """(doc_id, node, n, keys) of every text with words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                tokens, ptr = _token_sets(buf, offs, width)
                have = np.flatnonzero(np.diff(ptr))
                if not len(have):
                    continue
                ptr = np.append(ptr[have], ptr[-1])
                keys = pa.FixedSizeListArray.from_arrays(pa.array(signed(_band_keys(tokens, ptr).ravel())), BANDS).cast(pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([rows.column(0).take(pa.array(have)), pa.array(signed(_fingerprints(tokens, ptr))), pa.array(np.diff(ptr).astype(np.int32)), keys], ["doc_id", "node", "n", "keys"])

    return keyed_docs(docs).where("doc_id is not null").mapInArrow(run, "doc_id long, node long, n int, keys array<long>")


def _token_arrays(table: pa.Table, order: np.ndarray) -> list[np.ndarray]:
    """The token sets of the rows in order, as views of the table's own bytes."""
    raw = table["tokens"].combine_chunks().cast(pa.large_binary())
    offs = np.frombuffer(raw.buffers()[1], np.int64)[raw.offset : raw.offset + len(raw) + 1]
    data = np.frombuffer(raw.buffers()[2], np.uint8)
    return [data[offs[i] : offs[i + 1]].view(np.uint64) for i in order]


def _opened(sets: list[np.ndarray], m: int, threshold: float, own: bool) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(q, rows of members, their similarity) of each row with a partner among the first m, the members; pairs of members once, and only if own."""
    if not m:
        return
    share = threshold / (1 + threshold)
    size = np.array([len(x) for x in sets], np.int64)
    union, column = np.unique(np.concatenate(sets[:m]), return_inverse=True)
    owner = np.repeat(np.arange(m, dtype=np.int32), size[:m])[np.argsort(column, kind="stable")]
    ptr = np.concatenate([[0], np.cumsum(np.bincount(column, minlength=len(union)))])
    edge = np.concatenate([[0], np.cumsum(size[:m])])
    ahead = ptr[:-1].copy()  # of each token's members, the first behind the rows that are done
    least = size[:m].min()
    for q in range(0 if own else m, len(sets)):
        if q < m:
            cols = column[edge[q] : edge[q + 1]]
            ahead[cols] += 1
            first = ahead[cols]
        else:
            at = np.searchsorted(union, sets[q])
            at[at == len(union)] = 0
            cols = at[union[at] == sets[q]]
            if len(cols) < share * (size[q] + least):
                continue
            first = ptr[cols]
        lens = ptr[cols + 1] - first
        meets = owner[np.repeat(first - (np.cumsum(lens) - lens), lens) + np.arange(lens.sum())]
        if len(meets) < m // 8:
            at, common = np.unique(meets, return_counts=True)
        else:
            common = np.bincount(meets, minlength=m)
            at = np.flatnonzero(common)
            common = common[at]
        j = common / (size[q] + size[at] - common)
        good = j >= threshold
        if good.any():
            yield q, at[good], j[good]


class _Forest:
    """Connected components of rows; as many steps over all rows as there are unions."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def link(self, q: int, to: np.ndarray) -> None:
        label = self.label
        for r in np.unique(label[to]).tolist():
            mine = label[q]
            if r != mine:
                label[label == max(r, mine)] = min(r, mine)

    def edges(self, name: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(lesser, greater) names of a spanning forest."""
        row = np.flatnonzero(self.label != np.arange(len(self.label)))
        a, b = name[self.label[row]], name[row]
        lo, hi = np.minimum(a, b), np.maximum(a, b)
        return lo[lo != hi], hi[lo != hi]


def _rows(table: pa.Table) -> tuple[np.ndarray, int, bool]:
    """Order of the rows with the members first; how many they are; whether this block has the pairs of its members."""
    member = table["member"].to_numpy(zero_copy_only=False)
    own = "lo" not in table.column_names or table["lo"][0] == table["hi"][0]
    return np.argsort(~member, kind="stable"), int(member.sum()), own


def _matrix_join(threshold: float, spanning: bool, key: str = "rep"):
    def open_group(table: pa.Table) -> pa.Table:
        order, m, own = _rows(table)
        rep = table[key].to_numpy()[order]
        left, right, sim = [np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0)]
        forest = _Forest(len(rep))
        for q, to, j in _opened(_token_arrays(table, order), m, threshold, own):
            if spanning:
                forest.link(q, to)
            else:
                other = rep[to] != rep[q]
                left.append(np.full(int(other.sum()), rep[q]))
                right.append(rep[to[other]])
                sim.append(j[other])
        a, b, s = np.concatenate(left), np.concatenate(right), np.concatenate(sim)
        lo, hi = np.minimum(a, b), np.maximum(a, b)
        if spanning:
            lo, hi = forest.edges(rep)
            s = np.ones(len(lo))
        return pa.table({"doc_id_a": pa.array(lo, pa.int64()), "doc_id_b": pa.array(hi, pa.int64()), "jaccard": pa.array(np.round(s, 6), pa.float64())})

    return open_group


def _matrix_links(threshold: float):
    """Of an opened group a spanning forest of representatives (a, b), and for each node a the number of texts in the nodes linked to it."""

    def open_group(table: pa.Table) -> pa.Table:
        order, m, own = _rows(table)
        rep, node, texts = (table[c].to_numpy()[order] for c in ("rep", "node", "texts"))
        links = np.zeros(len(node), np.int64)
        forest = _Forest(len(node))
        for q, to, _ in _opened(_token_arrays(table, order), m, threshold, own):
            forest.link(q, to)
            links[q] += texts[to].sum()
            links[to] += texts[q]
        lo, hi = forest.edges(rep)
        some = np.flatnonzero(links)
        a, b, n = np.concatenate([lo, node[some]]), np.concatenate([hi, np.zeros(len(some), np.int64)]), np.concatenate([np.zeros(len(lo), np.int64), links[some]])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "links": pa.array(n, pa.int64())})

    return open_group


def join(docs: DataFrame, threshold: float = THRESHOLD, width: int = WIDTH, spanning: bool = False) -> tuple[DataFrame, DataFrame]:
    """The pairs, and (doc_id, node) of all rows with words. With spanning, only a spanning forest of each opened group."""
    pairs, sig = _pairs(docs, threshold, width, spanning)
    ids = sig.select("doc_id", "node").distinct()
    return pairs.unionByName(_copies(sig, ids).withColumn("jaccard", F.lit(1.0))), ids


def _copies(sig: DataFrame, ids: DataFrame) -> DataFrame:
    """One pair of each further text of an equal set with its representative."""
    return ids.join(sig.groupBy("node").agg(F.min("doc_id").alias("rep"), F.max("doc_id").alias("most")).where("most > rep"), "node").where("doc_id <> rep").select(F.col("rep").alias("doc_id_a"), F.col("doc_id").alias("doc_id_b"))


def _pairs(docs: DataFrame, threshold: float, width: int, spanning: bool = False, by: str = "rep") -> tuple[DataFrame, DataFrame]:
    """The pairs of different sets, named by their representatives or, with by='node', by their nodes; and the signatures."""
    opened, sig = _blocks(docs, width)
    return opened.applyInArrow(_matrix_join(threshold, spanning, by), "doc_id_a long, doc_id_b long, jaccard double"), sig


def _blocks(docs: DataFrame, width: int, counted: bool = False) -> tuple[GroupedData, DataFrame]:
    """Nodes with their sets, and if counted their numbers of texts, in the blocks in which they meet, grouped by block; and the signatures."""
    sig = cut(signatures(docs, width))
    nodes = sig.groupBy("node").agg(F.min("doc_id").alias("rep"), F.min("n").alias("n"), F.first("keys").alias("keys"))

    buckets = cut(nodes.select("node", F.explode("keys").alias("key")).groupBy("key").agg(F.array_sort(F.collect_list("node")).alias("nodes")).where(F.size("nodes") > 1).select("nodes").distinct())
    seats = buckets.select(F.col("nodes")[0].alias("least"), F.explode("nodes").alias("node"))
    group = cut(seats.groupBy("node").agg(F.min("least").alias("g")))
    # groups that meet in a bucket
    meet = buckets.select(F.xxhash64("nodes").alias("b"), F.explode("nodes").alias("node")).join(group, "node").groupBy("b").agg(F.collect_set("g").alias("gs"), F.collect_list(F.struct("node", "g")).alias("of")).where(F.size("gs") > 1)
    probes = meet.select("gs", F.explode("of").alias("x")).select(F.col("x.node").alias("node"), F.col("x.g").alias("own"), F.explode("gs").alias("g")).where("g < own").select("node", "g").distinct()

    active = cut(nodes.select("node", "rep", "n").join(group, "node"))
    probes = cut(probes.join(active.select("node", "n"), "node"))
    sets = _sets_of(docs, active.select("node", "rep"), width)
    if counted:
        sets = sets.join(sig.select("doc_id", "node").distinct().groupBy("node").agg(F.count("*").alias("texts")), "node")
    return _places(active, probes).join(sets, "node").groupBy("g", "lo", "hi"), sig


def _places(active: DataFrame, probes: DataFrame) -> DataFrame:
    """(node, g, lo, hi, member): the members of a group and the nodes that probe it are dealt to blocks of about BLOCK_TOKENS.

    Block (lo, lo) has the pairs of members lo and, with them, the first block of probes; a block lo < hi has members lo
    with members hi or, from the number of member blocks on, with a block of probes. Members of lo have the flag.
    """
    count = lambda df, name: df.groupBy("g").agg(F.ceil(F.sum(F.col("n").cast("long")) / BLOCK_TOKENS).cast("int").alias(name))
    sizes = count(active, "blocks").join(count(probes, "foreign"), "g", "left").fillna(0, ["foreign"])
    deal = lambda df, over: df.join(sizes, "g").select("node", "g", "blocks", "foreign", F.pmod(F.xxhash64("node"), F.col(over)).cast("int").alias("own"))
    seat, probe = deal(active, "blocks"), deal(probes, "foreign")
    span = lambda low, high: F.explode(F.when(high > low, F.sequence(low, high - 1)))
    own, blocks, zero = F.col("own"), F.col("blocks"), F.lit(0)
    first = seat.select("node", "g", own.alias("lo"), own.alias("hi"), F.lit(True).alias("member"))
    later = seat.select("node", "g", own.alias("lo"), span(own + 1, blocks).alias("hi"), F.lit(True).alias("member"))
    before = seat.select("node", "g", span(zero, own).alias("lo"), own.alias("hi"), F.lit(False).alias("member"))
    opened = seat.select("node", "g", own.alias("lo"), span(blocks + 1, blocks + F.col("foreign")).alias("hi"), F.lit(True).alias("member"))
    probing = probe.select("node", "g", "blocks", "own", span(zero, blocks).alias("lo")).select("node", "g", "lo", F.when(own == 0, F.col("lo")).otherwise(blocks + own).alias("hi"), F.lit(False).alias("member"))
    return first.unionByName(later).unionByName(before).unionByName(opened).unionByName(probing)


def classes(docs: DataFrame, threshold: float = THRESHOLD, width: int = WIDTH) -> DataFrame:
    """(doc_id, class_id, links) of every id. No pair of texts is written, only forests and sums of the opened groups."""
    opened, sig = _blocks(docs, width, counted=True)
    found = cut(opened.applyInArrow(_matrix_links(threshold), "a long, b long, links long"))
    ids = sig.select("doc_id", "node").distinct()
    edges = found.where("links = 0").select(F.col("a").alias("doc_id_a"), F.col("b").alias("doc_id_b")).unionByName(_copies(sig, ids))
    near = found.where("links > 0").select(F.col("a").alias("node"), "links")
    # a text's links: the further texts of its node, and those of the nodes linked to it
    by_node = ids.groupBy("node").agg((F.count("*") - 1).alias("links")).unionByName(near).groupBy("node").agg(F.sum("links").alias("links")).where("links > 0")
    links = ids.join(by_node, "node").groupBy("doc_id").agg(F.sum("links").alias("links"))
    every = docs.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    return every.join(components(edges), "doc_id", "left").join(links, "doc_id", "left").select("doc_id", F.coalesce("root", "doc_id").alias("class_id"), F.coalesce("links", F.lit(0)).alias("links"))


def every_pair(docs: DataFrame, threshold: float = THRESHOLD, width: int = WIDTH) -> DataFrame:
    """All pairs of texts. The texts of a node are listed once; BLOCK_IDS of one side with all of the other are a row that expands where it lands."""
    pairs, sig = _pairs(docs, threshold, width, by="node")
    ids = cut(sig.select("doc_id", "node").distinct())
    of = ids.groupBy("node").agg(F.collect_list("doc_id").alias("texts"))
    a, b = of.toDF("doc_id_a", "left"), of.toDF("doc_id_b", "right")
    both = pairs.join(a, "doc_id_a").join(b, "doc_id_b").select("doc_id_a", "doc_id_b", "left", "right", "jaccard")
    own = of.where(F.size("texts") > 1).select(F.col("node").alias("doc_id_a"), F.col("node").alias("doc_id_b"), F.col("texts").alias("left"), F.col("texts").alias("right"), F.lit(1.0).alias("jaccard"))
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = both.unionByName(own).withColumn("block", F.explode(F.sequence(F.lit(0), F.floor((F.size("left") - 1) / BLOCK_IDS).cast("int"))))
    blocks = blocks.withColumn("left", F.slice("left", F.col("block") * BLOCK_IDS + 1, F.lit(BLOCK_IDS))).repartition(n, "doc_id_a", "doc_id_b", "block")
    sides = blocks.withColumn("x", F.explode("left")).drop("left").withColumn("y", F.explode("right"))
    out = sides.where("case when doc_id_a = doc_id_b then x < y else x <> y end").select(F.least("x", "y").alias("doc_id_a"), F.greatest("x", "y").alias("doc_id_b"), "jaccard")
    if ids.groupBy("doc_id").count().where("count > 1").isEmpty():
        return out
    return out.groupBy("doc_id_a", "doc_id_b").agg(F.max("jaccard").alias("jaccard"))  # an id with several texts: its best pair


def _sets_of(docs: DataFrame, active: DataFrame, width: int) -> DataFrame:
    """(node, rep, n, tokens) of the representatives in active."""
    reps = active.select(F.col("rep").alias("doc_id")).distinct()
    reps = F.broadcast(reps) if active.count() <= BROADCAST_IDS else reps
    rows = keyed_docs(docs).where("doc_id is not null").join(reps, "doc_id", "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, buf, offs in byte_slices(batch):
                tokens, ptr = _token_sets(buf, offs, width)
                have = np.flatnonzero(np.diff(ptr))
                if not len(have):
                    continue
                ptr = np.append(ptr[have], ptr[-1])
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(have)), pa.array(signed(_fingerprints(tokens, ptr))), pa.array(np.diff(ptr).astype(np.int32)), pa.array([tokens[a:b].tobytes() for a, b in zip(ptr[:-1], ptr[1:])], pa.binary())], ["rep", "node", "n", "tokens"])

    found = rows.mapInArrow(run, "rep long, node long, n int, tokens binary")
    # an id with several texts, or repeated rows: the one text of the node, once
    return found.join(active.withColumnRenamed("rep", "of"), "node").where("rep = of").drop("of").dropDuplicates(["node"])


def expand(pairs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """All pairs of texts: each side of a pair of representatives stands for every text of its set."""
    same = pairs.where("jaccard = 1")
    sides = same.select(F.col("doc_id_a").alias("rep"), F.col("doc_id_b").alias("id")).unionByName(pairs.select(F.explode(F.array("doc_id_a", "doc_id_b")).alias("rep")).distinct().select("rep", F.col("rep").alias("id")))
    a, b = sides.toDF("doc_id_a", "a"), sides.toDF("doc_id_b", "b")
    cross = pairs.where("jaccard < 1").join(a, "doc_id_a").join(b, "doc_id_b")
    inner = same.select("doc_id_a").distinct().join(a, "doc_id_a").join(sides.toDF("doc_id_a", "b"), "doc_id_a").where("a < b").withColumn("jaccard", F.lit(1.0))
    return cross.select("a", "b", "jaccard").unionByName(inner.select("a", "b", "jaccard")).select(F.least("a", "b").alias("doc_id_a"), F.greatest("a", "b").alias("doc_id_b"), "jaccard").distinct()


def components(pairs: DataFrame) -> DataFrame:
    """(doc_id, root) of every id in a pair; root is the least id of its connected component."""
    edges = cut(pairs.select(F.col("doc_id_a").alias("u"), F.col("doc_id_b").alias("v")).distinct())
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    label = cut(both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("root")))
    while True:
        near = both.join(label.select(F.col("u").alias("v"), "root"), "v").groupBy("u").agg(F.min("root").alias("near"))
        low = label.join(near, "u").select("u", F.least("root", "near").alias("low"), F.col("root").alias("before"))
        jump = low.join(low.select(F.col("u").alias("low"), F.col("low").alias("far")), "low", "left").select("u", F.coalesce(F.least("low", "far"), "low").alias("root"), "before")
        done = cut(jump)
        label = done.select("u", "root")
        if done.where("root <> before").isEmpty():
            return label.withColumnRenamed("u", "doc_id")


def keep_one(docs: DataFrame, threshold: float = THRESHOLD, width: int = WIDTH) -> DataFrame:
    """The rows of docs without those whose group of near duplicates holds a lesser id; of repeated rows one stays."""
    pairs, ids = join(docs, threshold, width, spanning=True)
    gone = cut(components(pairs).where("root <> doc_id").select("doc_id"))
    few = gone.count() <= BROADCAST_IDS
    kept = docs.join(F.broadcast(gone) if few else gone, "doc_id", "left_anti")
    twice = docs.groupBy("doc_id").count().where("count > 1 and doc_id is not null").select("doc_id")
    twice = cut(twice)
    if twice.isEmpty():
        return kept.select(*docs.columns)
    once = kept.join(twice, "doc_id", "left_anti")
    return once.select(*docs.columns).unionByName(kept.join(twice, "doc_id", "left_semi").select(*docs.columns).dropDuplicates(["doc_id", "text"]))


def op6_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(load(spark, sf_dir, "documents"))
