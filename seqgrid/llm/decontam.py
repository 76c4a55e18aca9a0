"""Operator 3, benchmark decontamination by latent semantic retrieval.

1. *Passages.* Benchmark items are cut in passages of PASSAGE words; a document is read in windows of twice that, one
   passage apart, so every passage-long stretch lies whole in some window.
2. *TF-IDF.* Document frequencies of the benchmark's words are counted over all documents, by one scan. The weight is the
   square of a smoothed inverse document frequency, small for common words but never nothing.
3. *Randomised SVD.* One basis of RANK directions (fewer than half of the passages) for all passages: subspace iteration
   from a Gaussian sketch, POWER times. Each product is a distributed one over the table of passages: a task multiplies
   its rows, partial sums are added up by blocks of the vocabulary, and only the thin (words x directions) matrix, which
   does not grow with the corpus, reaches the driver to be made orthogonal.
4. *Search.* Every window is folded into the basis; windows of cosine >= MIN_COSINE with a passage, that can hold
   LCS_MAYBE of its words (no common subsequence is longer than the overlap of words) and have words of MIN_COVER of its
   weight (what common words make alike by chance has less), are candidates.
5. *Overlap.* So is every window whose words fill at least LCS_SURE of the passage's places (all places of a short
   item), whatever they weigh. No common subsequence is longer than this overlap, so no leak of LCS_SURE is missed,
   whatever its cosine. The answer's weaker rule in step 6 is for candidates of step 4.
6. *Checks.* Longest common subsequence of words (bit-parallel), as a share of the passage: at least LCS_SURE is a
   leak; from LCS_MAYBE on, it is one when the answer (the item's last ANSWER words) is common to ANSWER_SHARE.

All texts are read twice, by two maps without a shuffle of text. What is broadcast is the model and the words of up to
PASS passages; a larger benchmark takes further search passes over the documents, of at most PASS passages each.

Result of find(): one row (doc_id, item_id, cosine, lcs, answer, passage, position) for each leak of an item in a
document, its best window. Defined results: null or empty texts match nothing, items without words are ignored,
items of fewer than MIN_WORDS words match only by their whole sequence (share 1); null ids are reported as null;
repeated rows give one row for each (document id, item); an empty table on either side gives none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import byte_slices, cut, keyed_docs, load, mix, word_table

PASSAGE, RANK, OVERSAMPLE, POWER, PASS = 64, 64, 16, 2, 2048
MIN_COSINE, MIN_COVER, LCS_SURE, LCS_MAYBE, ANSWER, ANSWER_SHARE, MIN_WORDS = 0.3, 0.4, 0.7, 0.5, 6, 0.8, 8
BLOCK_WORDS = 4096
BROADCAST_IDS = 4 << 20
_BITS = 20


def passages(benchmark: DataFrame) -> DataFrame:
    """(item_id, passage, words, answer) with words as 64-bit hashes; the last passage of an item starts earlier rather than being short."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                _, _, h, doc = word_table(buf, offs)
                ids = rows.column(0).to_pylist()
                out = []
                for i, item in enumerate(ids):
                    w = h[doc == i]
                    starts = list(range(0, max(len(w) - PASSAGE, 0) + 1, PASSAGE))
                    if len(w) > PASSAGE and starts[-1] + PASSAGE < len(w):
                        starts.append(len(w) - PASSAGE)
                    out += [(item, k, w[s : s + PASSAGE].tobytes(), w[-ANSWER:].tobytes()) for k, s in enumerate(starts) if len(w)]
                if out:
                    a, b, c, d = zip(*out)
                    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int32()), pa.array(c, pa.binary()), pa.array(d, pa.binary())], ["item_id", "passage", "words", "answer"])

    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "item_id long, passage int, words binary, answer binary")


class Vocabulary:
    """Exact look-up of word hashes; a bitmap lets most words of other texts go at once."""

    def __init__(self, hashes: np.ndarray):
        self.hashes = np.unique(hashes)
        self.seen = np.zeros(1 << _BITS, bool)
        self.seen[(self.hashes & np.uint64((1 << _BITS) - 1)).astype(np.int64)] = True

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions in h, indices) of the words that are in the vocabulary."""
        maybe = np.flatnonzero(self.seen[(h & np.uint64((1 << _BITS) - 1)).astype(np.int64)])
        if not len(maybe) or not len(self.hashes):
            return np.empty(0, np.int64), np.empty(0, np.int64)
        at = np.searchsorted(self.hashes, h[maybe])
        at[at == len(self.hashes)] = 0
        ok = self.hashes[at] == h[maybe]
        return maybe[ok], at[ok]


def document_frequencies(docs: DataFrame, vocab: np.ndarray) -> tuple[np.ndarray, int]:
    """In how many documents each word of vocab is, and how many documents there are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, df, n = Vocabulary(vocab), np.zeros(len(vocab), np.int64), 0
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                _, _, h, doc = word_table(buf, offs)
                at, f = known.find(h)
                df += np.bincount(np.unique(doc[at] * len(vocab) + f) % len(vocab), minlength=len(vocab))
                n += rows.num_rows
        have = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(have, -1)), pa.array(np.append(df[have], n))], ["f", "n"])

    out, n = np.zeros(len(vocab), np.int64), 0
    for r in keyed_docs(docs).mapInArrow(run, "f long, n long").groupBy("f").agg(F.sum("n").alias("n")).collect():
        if r["f"] < 0:
            n = r["n"]
        else:
            out[r["f"]] = r["n"]
    return out, n


def gaussian(h: np.ndarray, k: int, seed: int = 11) -> np.ndarray:
    """A row of k normal numbers for each word, from its hash alone: every task draws the same ones."""
    with np.errstate(over="ignore"):
        u = mix(h[:, None] + (np.arange(2 * k, dtype=np.uint64) + np.uint64(seed * 1000 + 1)) * np.uint64(0x9E3779B97F4A7C15))
    u = ((u >> np.uint64(11)).astype(np.float64) + 1) / (1 << 53)
    return np.sqrt(-2 * np.log(u[:, :k])) * np.cos(2 * np.pi * u[:, k:])


def _weighted(words: list[bytes], vocab: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sparse TF-IDF rows: (row, place among used, weight), and the vocabulary's numbers of the used words."""
    at = [np.searchsorted(vocab, np.frombuffer(w, np.uint64)) for w in words]
    flat = np.concatenate(at)
    used, local = np.unique(flat, return_inverse=True)
    return np.repeat(np.arange(len(at)), [len(x) for x in at]), local, idf[flat], used


def _times(row: np.ndarray, col: np.ndarray, value: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    """Sparse (n rows) by dense; entries come in order of rows, and every row has some."""
    return np.add.reduceat(value[:, None] * x[col], np.searchsorted(row, np.arange(n)), axis=0)


def _back(row: np.ndarray, col: np.ndarray, value: np.ndarray, y: np.ndarray, n: int) -> np.ndarray:
    """Transposed sparse by dense, n columns of the sparse one."""
    order = np.argsort(col, kind="stable")
    return np.add.reduceat(value[order, None] * y[row[order]], np.searchsorted(col[order], np.arange(n)), axis=0)


def randomised_svd(passage: DataFrame, vocab: np.ndarray, idf: np.ndarray, rank: int, power: int = POWER) -> tuple[np.ndarray, np.ndarray]:
    """(leading right singular vectors as columns, singular values) of the TF-IDF rows of passages (words binary, not empty), by distributed products."""
    sc = passage.sparkSession.sparkContext
    k = rank + OVERSAMPLE

    def product(x: np.ndarray | None) -> np.ndarray:
        """Transposed rows times (rows times x), or times a Gaussian sketch."""
        shared = sc.broadcast((vocab, idf, x))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            vocab, idf, x = shared.value
            for batch in batches:
                if not batch.num_rows:
                    continue
                row, col, value, used = _weighted(batch.column(0).to_pylist(), vocab, idf)
                y = _times(row, col, value, gaussian(vocab[used], k) if x is None else x[used], batch.num_rows)
                z = _back(row, col, value, y, len(used))
                edge = np.flatnonzero(np.diff(used // BLOCK_WORDS, prepend=-1))
                to = np.append(edge[1:], len(used))
                yield pa.RecordBatch.from_arrays([pa.array(used[edge] // BLOCK_WORDS), pa.array([used[a:b].tobytes() for a, b in zip(edge, to)], pa.binary()), pa.array([z[a:b].tobytes() for a, b in zip(edge, to)], pa.binary())], ["block", "at", "sums"])

        def add(table: pa.Table) -> pa.Table:
            block = table["block"][0].as_py()
            out = np.zeros((BLOCK_WORDS, k))
            parts = sorted(zip(table["at"].to_pylist(), table["sums"].to_pylist()))  # one order of summing, so one result
            for at, sums in parts:
                out[np.frombuffer(at, np.int64) - block * BLOCK_WORDS] += np.frombuffer(sums).reshape(-1, k)
            return pa.table([pa.array([block]), pa.array([out.tobytes()], pa.binary())], ["block", "sums"])

        z = np.zeros((len(vocab), k))
        for r in passage.select("words").mapInArrow(run, "block long, at binary, sums binary").groupBy("block").applyInArrow(add, "block long, sums binary").collect():
            lo = r["block"] * BLOCK_WORDS
            z[lo : lo + BLOCK_WORDS] = np.frombuffer(r["sums"]).reshape(-1, k)[: len(vocab) - lo]
        return z

    x = None
    for _ in range(power + 1):
        x = np.linalg.qr(product(x))[0]
        x = np.pad(x, ((0, 0), (0, k - x.shape[1])))  # a vocabulary of fewer words than directions
    s, u = np.linalg.eigh(x.T @ product(x))
    order = np.argsort(s)[::-1][:rank]
    s = np.sqrt(np.maximum(s[order], 0))
    keep = max(1, int((s > 1e-6 * max(s[0], 1e-30)).sum()))
    return (x @ u[:, order])[:, :keep], s[:keep]


def lcs(a: np.ndarray, b: np.ndarray) -> int:
    """Length of the longest common subsequence, one machine-integer step for each element of b."""
    at: dict[int, int] = {}
    for i, x in enumerate(a.tolist()):
        at[x] = at.get(x, 0) | (1 << i)
    full = (1 << len(a)) - 1
    s = full
    for x in b.tolist():
        m = at.get(x)
        if m:
            u = s & m
            s = ((s + u) | (s - u)) & full
    return len(a) - s.bit_count()


def judge(item: np.ndarray, answer: np.ndarray, window: np.ndarray) -> tuple[float, float, bool]:
    share = lcs(item, window) / len(item)
    if share < LCS_MAYBE:
        return share, 0.0, False
    told = lcs(answer, window) / len(answer)
    if len(item) < MIN_WORDS:
        return share, told, share == 1
    return share, told, share >= LCS_SURE or told >= ANSWER_SHARE


def _places(items: list[np.ndarray], vocab: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """In how many places of each item each word stands (PASSAGE at most), the most in any item, and the places that a sure and a possible leak must fill."""
    places = np.zeros((len(vocab), len(items)), np.uint8)
    for j, w in enumerate(items):
        np.add.at(places, (np.searchsorted(vocab, w), j), 1)
    need = lambda share: np.array([len(w) if len(w) < MIN_WORDS else np.ceil(share * len(w) - 1e-9) for w in items])
    return places, places.max(axis=1).astype(np.int64), need(LCS_SURE), need(LCS_MAYBE)


def _windows(block: np.ndarray, f: np.ndarray, first: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct words of each window (a block with a known word and the next of the same text): windows, words, and where each window's words begin."""
    pair = np.unique(block * n + f)
    at = pair // n
    before = pair[~np.isin(at, first)] - n
    both = np.unique(np.concatenate([pair, before[np.isin(before // n, at)]]))
    windows, edge = np.unique(both // n, return_index=True)
    return windows, both % n, edge


def _overlaps(chosen: np.ndarray, words: np.ndarray, edge: np.ndarray, places: np.ndarray) -> np.ndarray:
    """(chosen windows x items): how many places of each item the window's words fill."""
    size = np.diff(np.append(edge, len(words)))
    begin = np.concatenate([[0], np.cumsum(size[chosen])[:-1]])
    return np.add.reduceat(places[words[np.repeat(chosen, size)]], begin, axis=0, dtype=np.int32)


def _covered(w: np.ndarray, j: np.ndarray, sure: np.ndarray, chosen: np.ndarray, words: np.ndarray, edge: np.ndarray, places: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sure pairs, and those whose window has words of MIN_COVER of the item's weight: chance hits share common words only."""
    lo, size = edge[chosen[w]], np.diff(np.append(edge, len(words)))[chosen[w]]
    begin = np.concatenate([[0], np.cumsum(size)[:-1]])
    at = words[np.arange(size.sum()) - np.repeat(begin - lo, size)]
    have = np.add.reduceat(places[at, np.repeat(j, size)] * weight[at], begin)
    keep = sure | (have >= MIN_COVER * (weight @ places)[j])
    return w[keep], j[keep]


def _search(docs: DataFrame, rows: list[dict], vocab: np.ndarray, basis: np.ndarray, places: np.ndarray, weight: np.ndarray) -> DataFrame:
    """Leaks of these passages; basis: the vocabulary's rows of the basis times their weight, places: the passages' own."""
    items = [np.frombuffer(r["words"], np.uint64) for r in rows]
    answers = [np.frombuffer(r["answer"], np.uint64) for r in rows]
    item_ids = np.array([r["item_id"] for r in rows], dtype=object)
    numbers = np.array([r["passage"] for r in rows])
    shared = docs.sparkSession.sparkContext.broadcast((items, answers, item_ids, numbers, vocab, basis.astype(np.float32), places.astype(np.float32), weight))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items, answers, item_ids, numbers, vocab, basis, place, weight = shared.value
        known = Vocabulary(vocab)
        norm = np.maximum(np.linalg.norm(place, axis=1), 1e-9)
        filled, most, sure, maybe = _places(items, vocab)
        for batch in batches:
            for part, buf, offs in byte_slices(batch):
                _, _, h, doc = word_table(buf, offs)
                at, f = known.find(h)
                if not len(at):
                    continue
                first = np.searchsorted(doc, np.arange(len(offs)))  # first word of each text
                counts = np.diff(first)
                n_blocks = -(-counts // PASSAGE)
                block0 = np.concatenate([[0], np.cumsum(n_blocks)])
                hit_block = block0[doc[at]] + (at - first[doc[at]]) // PASSAGE
                windows, words, edge = _windows(hit_block, f, block0, len(vocab))
                # a window that can't fill LCS_MAYBE of any passage has no leak
                chosen = np.add.reduceat(most[words], edge) >= maybe.min()
                if not chosen.any():
                    continue
                touched, start = np.unique(hit_block, return_index=True)
                sums = np.add.reduceat(basis[f], start, axis=0)
                mine = windows[chosen]
                z = np.zeros((len(mine), basis.shape[1]), np.float32)
                for step in (0, 1):  # a window is a block and the next one of its text
                    k = np.minimum(np.searchsorted(touched, mine + step), len(touched) - 1)
                    ok = touched[k] == mine + step
                    if step:
                        ok &= ~np.isin(mine + 1, block0)
                    z[ok] += sums[k[ok]]
                cosine = (z @ place.T) / np.maximum(np.linalg.norm(z, axis=1), 1e-9)[:, None] / norm[None, :]
                overlap = _overlaps(chosen, words, edge, filled)
                w, j = np.nonzero((overlap >= sure) | ((cosine >= MIN_COSINE) & (overlap >= maybe)))
                if not len(w):
                    continue
                w, j = _covered(w, j, overlap[w, j] >= sure[j], np.flatnonzero(chosen), words, edge, filled, weight)
                found = [(int(mine[i]), int(q), float(cosine[i, q])) for i, q in zip(w, j)]
                best: dict[tuple[int, int], tuple] = {}
                for b, j, cos in found:
                    d = int(np.searchsorted(block0, b, side="right")) - 1
                    lo = first[d] + (b - block0[d]) * PASSAGE
                    share, told, leak = judge(items[j], answers[j], h[lo : min(lo + 2 * PASSAGE, first[d + 1])])
                    if leak and (share >= LCS_SURE or cos >= MIN_COSINE):
                        key, new = (d, item_ids[j]), (round(share, 4), round(told, 4), round(cos, 4), -int(numbers[j]), -int(lo - first[d]))
                        if key not in best or new > best[key]:
                            best[key] = new
                if best:
                    ids = part.column(0).to_pylist()
                    out = [(ids[d], int(item), v[2], v[0], v[1], -v[3], -v[4]) for (d, item), v in best.items()]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.int32(), pa.int32()])], ["doc_id", "item_id", "cosine", "lcs", "answer", "passage", "position"])

    return keyed_docs(docs).mapInArrow(run, "doc_id long, item_id long, cosine double, lcs double, answer double, passage int, position int")


EMPTY = "doc_id long, item_id long, cosine double, lcs double, answer double, passage int, position int"


def find(docs: DataFrame, benchmark: DataFrame, rank: int = RANK, most: int = PASS) -> DataFrame:
    spark = docs.sparkSession
    passage = cut(passages(benchmark.where("item_id is not null")).dropDuplicates(["words", "item_id"]))
    rows = sorted((r.asDict() for r in passage.collect()), key=lambda r: (r["item_id"], r["passage"]))
    if not rows:
        return spark.createDataFrame([], EMPTY)
    vocab = np.unique(np.concatenate([np.frombuffer(r["words"], np.uint64) for r in rows]))
    df, n_docs = document_frequencies(docs, vocab)
    weight = np.log((n_docs + 2) / (df + 1)) ** 2
    v, _ = randomised_svd(passage, vocab, weight, min(rank, max(1, len(rows) // 2)))
    basis = v * weight[:, None]
    out = None
    for lo in range(0, len(rows), most):
        part = rows[lo : lo + most]
        words = np.unique(np.concatenate([np.frombuffer(r["words"], np.uint64) for r in part]))
        mine = np.searchsorted(vocab, words)
        places = np.stack([basis[np.searchsorted(vocab, np.frombuffer(r["words"], np.uint64))].sum(0) for r in part])
        hits = _search(docs, part, words, basis[mine], places, weight[mine])
        out = hits if out is None else out.unionByName(hits)
    best = F.max_by(F.struct("cosine", "lcs", "answer", "passage", "position"), F.struct("lcs", "answer", "cosine", -F.col("passage"), -F.col("position"))).alias("x")
    return out.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "x.*")


def drop_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs, all columns, in which no item was found."""
    bad = cut(find(docs, benchmark).where("doc_id is not null").select("doc_id").distinct())
    return docs.join(F.broadcast(bad) if bad.count() <= BROADCAST_IDS else bad, "doc_id", "left_anti").select(*docs.columns)


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))
