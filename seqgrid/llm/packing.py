"""Operator 1, packing: order-preserving dynamic programming with a monotone queue.

Documents keep the order of their ids. Their text is a stream of units, its sentences; the stream is cut in
windows of at most ``capacity`` tokens (words between white space). A window costs its padding; a cut inside a
document costs SPLIT more, and a cut inside a sentence HARD more (only sentences longer than a window offer such
cuts, after every ``capacity`` tokens). With S the running count of tokens, the best cost up to cut j is
min over cuts i with S[j] - S[i] <= capacity of f(i) + capacity - (S[j] - S[i]) + penalty(j): a sliding-window
minimum of f(i) + S(i), which the queue keeps in order, so a shard costs time linear in its units.

Shards are runs of SHARD_DOCS documents (those with words, in order of their ids, however the ids are spread) and are
packed independently, so each ends with one window that may be short; README has the padding that this adds. Units
are found by one map over whole texts; only their lengths are shuffled, never text: to ranges of ids, which give each
document its rank, and to shards.

Result: one row for each piece of a window: (shard, window, seq, doc_id, start_char, end_char, n_tokens,
window_tokens); start_char counts from 0. The pieces of a document cover it from 0 to its end. Defined results:
texts without tokens (null, empty, blank) have no piece; documents with a null id come first; equal ids are
ordered by a hash of the text; repeated rows are packed each.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqgrid.llm.common import IS_SPACE, byte_slices, cut, keyed_docs, load

CAPACITY, SPLIT, HARD, SHARD_DOCS = 2048, 64, 256, 2048
_MARK = np.zeros(256, bool)
_MARK[[33, 46, 63]] = True
RESULT = "shard long, window int, seq int, doc_id long, start_char int, end_char int, n_tokens int, window_tokens int"


def units(buf: np.ndarray, offs: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, end in characters, tokens, ends inside a sentence) of every unit, in order."""
    empty = np.empty(0, np.int64)
    if not len(buf):
        return empty, empty, empty, empty.astype(bool)
    space = IS_SPACE[buf]
    before = np.empty(len(buf), bool)
    before[0], before[1:] = True, space[:-1]
    before[offs[:-1][offs[:-1] < len(buf)]] = True
    word = np.flatnonzero(~space & before)
    if not len(word):
        return empty, empty, empty, empty.astype(bool)
    after = np.empty(len(buf), bool)
    after[-1], after[:-1] = True, space[1:]
    end = (_MARK[buf] & after) | (buf == 10)
    last = offs[1:][np.diff(offs) > 0] - 1
    end[last] = True
    stop = np.flatnonzero(end) + 1
    upto = np.searchsorted(word, stop)  # words before each stop
    doc = np.searchsorted(offs, stop - 1, side="right") - 1
    final = np.zeros(len(stop), bool)
    final[np.searchsorted(stop, last + 1)] = True
    # a stop that adds no word joins the next unit; at the end of a text it takes the place of the stop before it
    base = np.searchsorted(word, offs[doc])
    new = np.diff(np.concatenate([[0], upto])) > 0
    keep = new & (upto > base)
    where = np.flatnonzero(keep)
    shift = np.flatnonzero(final & ~keep)
    if len(shift):
        prev = np.searchsorted(where, shift) - 1
        ok = prev >= 0
        ok[ok] = doc[where[prev[ok]]] == doc[shift[ok]]
        stop[where[prev[ok]]] = stop[shift[ok]]
    stop, upto, doc = stop[keep], upto[keep], doc[keep]
    first = np.concatenate([[0], upto[:-1]])
    tokens = upto - first
    hard = np.zeros(len(stop), bool)
    if len(tokens) and tokens.max() > capacity:
        pieces = -(-tokens // capacity)
        row = np.repeat(np.arange(len(stop)), pieces)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        inner = nth < pieces[row] - 1
        upto_piece = np.where(inner, first[row] + (nth + 1) * capacity, upto[row])
        cut_at = np.where(inner, word[np.minimum(upto_piece, len(word) - 1)], stop[row])
        tokens, stop, doc, hard = np.where(inner, capacity, tokens[row] - nth * capacity), cut_at, doc[row], inner
    chars = np.concatenate([[0], np.cumsum((buf & 0xC0) != 0x80)])
    return doc, chars[stop] - chars[offs[doc]], tokens, hard


def best_cuts(tokens: np.ndarray, penalty: np.ndarray, capacity: int) -> tuple[list[int], int]:
    """Ends (unit counts) of the windows of least total cost, and that cost; ties take the longer last window."""
    n = len(tokens)
    total = np.concatenate([[0], np.cumsum(tokens)]).tolist()
    pen = penalty.tolist()
    back = [0] * (n + 1)
    queue: deque[tuple[int, int]] = deque([(0, 0)])  # (f(i) + S(i), i), rising
    cost = 0
    for j in range(1, n + 1):
        s = total[j]
        while s - total[queue[0][1]] > capacity:
            queue.popleft()
        g, i = queue[0]
        back[j] = i
        cost = g + capacity - s + pen[j - 1]
        g = cost + s
        while queue and queue[-1][0] > g:
            queue.pop()
        queue.append((g, j))
    cuts = []
    j = n
    while j:
        cuts.append(j)
        j = back[j]
    return cuts[::-1], cost


def _pack_shard(capacity: int, split: int, hard_cost: int):
    def run(table: pa.Table) -> pa.Table:
        table = table.take(pc.sort_indices(table, [("doc_id", "ascending"), ("tie", "ascending")], null_placement="at_start"))
        get = lambda c, t: [np.frombuffer(x, t) for x in table[c].to_pylist()]
        ends, toks, hards = get("ends", np.int32), get("tokens", np.int32), get("hard", np.uint8)
        count = np.array([len(x) for x in toks])
        doc = np.repeat(np.arange(len(count)), count)
        end, tok, hard = np.concatenate(ends), np.concatenate(toks), np.concatenate(hards)
        last = np.zeros(len(tok), bool)
        last[np.cumsum(count) - 1] = True
        cuts, _ = best_cuts(tok, np.where(last, 0, np.where(hard > 0, hard_cost, split)), capacity)
        window = np.repeat(np.arange(len(cuts)), np.diff([0, *cuts]))
        first = np.ones(len(tok), bool)
        first[1:] = (window[1:] != window[:-1]) | (doc[1:] != doc[:-1])
        at = np.flatnonzero(first)
        until = np.append(at[1:], len(tok)) - 1
        start = np.where(np.isin(at, np.cumsum(count) - count), 0, end[at - 1])
        w = window[at]
        wfirst = np.searchsorted(w, w)
        i32 = lambda x: pa.array(np.asarray(x).astype(np.int32))
        return pa.table([pa.array(np.full(len(at), table["shard"][0].as_py()), pa.int64()), i32(w), i32(np.arange(len(at)) - wfirst), table["doc_id"].combine_chunks().take(pa.array(doc[at])), i32(start), i32(end[until]), i32(np.add.reduceat(tok, at)), i32(np.bincount(window, tok)[w])], ["shard", "window", "seq", "doc_id", "start_char", "end_char", "n_tokens", "window_tokens"])

    return run


def pack(docs: DataFrame, capacity: int = CAPACITY, split: int = SPLIT, hard: int = HARD, shard_docs: int = SHARD_DOCS) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                doc, end, tokens, cut_inside = units(buf, offs, capacity)
                if not len(doc):
                    continue
                have, first = np.unique(doc, return_index=True)
                to = np.append(first[1:], len(doc))
                cols = [[x[a:b].tobytes() for a, b in zip(first, to)] for x in (end.astype(np.int32), tokens.astype(np.int32), cut_inside.astype(np.uint8))]
                take = pa.array(have)
                yield pa.RecordBatch.from_arrays([rows.column(0).take(take), rows.column(2).take(take), *[pa.array(c, pa.binary()) for c in cols]], ["doc_id", "tie", "ends", "tokens", "hard"])

    lengths = keyed_docs(docs).select("doc_id", "text", F.xxhash64("text").alias("tie")).mapInArrow(run, "doc_id long, tie long, ends binary, tokens binary, hard binary")
    # the ranges come from a sample, so they are kept; what other ranges hold before a document is a number for each
    ranged = cut(lengths.repartitionByRange("doc_id", "tie").withColumn("range", F.spark_partition_id()))
    before, rows = [], 0
    for r in ranged.groupBy("range").count().orderBy("range").collect():
        before.append((r["range"], rows))
        rows += r["count"]
    place = F.row_number().over(Window.partitionBy("range").orderBy(F.col("doc_id").asc_nulls_first(), "tie")) - 1
    ranked = ranged.withColumn("place", place).join(F.broadcast(docs.sparkSession.createDataFrame(before, "range int, before long")), "range")
    dealt = ranked.select(F.floor((F.col("before") + F.col("place")) / shard_docs).alias("shard"), "doc_id", "tie", "ends", "tokens", "hard")
    return dealt.groupBy("shard").applyInArrow(_pack_shard(capacity, split, hard), RESULT)


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(load(spark, sf_dir, "documents"))
