"""Operator 4, language-model scoring by cross-parsing against the rest of the corpus.

A document z, a sequence of n words, is factored greedily into the longest phrases that occur in reference text. With
c(z|r) phrases and c(z) phrases of z's own incremental (LZ78) parsing the scores are

    cross_entropy = c(z|r) * log2(n) / n         bits a word
    divergence    = (c(z|r) * log2(n) - c(z) * log2(c(z))) / n

a length-normalised estimate of the relative entropy of the document against the reference; lower is more alike.

The reference is the other documents of the corpus, all of them. score_whole(), which op4 returns, misses no match, and its
time and shuffle are about in proportion to the corpus. It finds for each word how long the longest match is that begins there:

* Texts are dealt to packs of about PACK_BYTES. A pack sends the hashes of its different runs of 2 words to ranges of hashes, where
  it is told which of them another pack has too; so each run is sent once a pack, however often it stands there, and no text is
  copied. Then the same for 3, 4, 5 and GRAM words, only for runs whose shorter runs are shared.
* Of a shared run of GRAM words the words before and behind are gathered too. A match of GRAM words or more can begin to reach
  further only where the words before a run differ (or a text begins), and can end only where the words behind one do. So
  only pairs of such starts and ends are asked for: the next RANKS ends behind each start.
* Texts with a match beyond all these (near copies with many edits) are joined by it to components. A bin of components sorts all
  places of its texts by what follows; beside a place stand the longest matches. In a bin too large for a task every two blocks of
  texts meet; only there the time can grow with the square, of the texts that are near copies of one another.

score() takes time in proportion to the corpus and misses matches; it finds them in two ways that one parse puts together:

1. *Suffix automata.* The documents of a language are dealt by a hash of the id into shards of about SHARD_BYTES, and
   each shard into two halves. The automaton of one half's text walks over the documents of the other half and tells
   for every word where the longest match that ends there begins. So each document is reference text once, has about
   SHARD_BYTES / 2 of reference, whatever the size of the corpus, and is never parsed against itself.
2. *Repeats over the whole corpus.* Texts are cut in chunks of about CHUNK words where a hash of two words says so, so
   equal passages have equal chunks wherever they stand. One aggregation over the chunks of all documents keeps those
   that stand in more than one; each of their places is told two others (the least and the greatest by document), and
   where neighbouring chunks go on together in another document, they are one match, however long.

A match of way 1 and one of way 2 are compared word by word, and the phrase is the longer. Missed are matches shorter than
about two chunks which only another shard holds, and longer ones where neighbouring chunks are told of no document in
common; README has the figure for what that does to the scores.
One shuffle of score() moves texts to their shards, two move chunk hashes, which are written once (about a fifth of a byte for each byte of text).

Words are lower-cased runs of word bytes (common.IS_WORD); letters of scripts without spaces (three and four byte
UTF-8) are words each. Defined results: null and empty texts and texts without words, and (for score()) texts which share no chunk
with another and whose half of a shard has no counterpart with words (one document in a language), have null scores; a null language is the language '';
rows with equal id and text are one document, not each other's reference, and get equal scores; equal texts with
different ids are each other's reference; null ids count as equal.
"""

from __future__ import annotations

import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import IS_WORD, _power_tables, byte_slices, keyed_docs, load, lowered, mix, signed, stored, word_table
from seqgrid.llm.jaccard import components

SHARD_BYTES = 8 << 20
CHUNK = 16
WHOLE = -1  # the number of a chunk that is a whole text
PACK_BYTES = 18 << 20
GRAM = 6  # matches of so many words and more are sought between branchings
RANKS = 16


def words(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hash, index of the text) of every word; letters of three and four bytes stand alone."""
    wide = buf >= 0xE2
    if not wide.any():
        _, _, h, doc = word_table(buf, offs)
        return h, doc
    # a space before and behind each wide letter
    lead = np.flatnonzero(wide)
    size = np.where(buf[lead] >= 0xF0, 4, 3)
    end = np.minimum(lead + size, len(buf))
    room = np.ones(len(buf), np.int64)
    room[lead] += 1
    np.add.at(room, end[end < len(buf)], 1)
    at = np.cumsum(room) - 1
    out = np.full(int(at[-1]) + 2, 32, np.uint8)
    out[at] = buf
    # a text begins where its first byte's room begins
    begin = np.concatenate([at - room + 1, [at[-1] + 1]])
    _, _, h, doc = word_table(out, begin[offs])
    return h, doc


def chunk_starts(h: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Places of the words that begin a chunk: the first of a text, and those behind a pair of words whose hash is a multiple of CHUNK."""
    if not len(h):
        return np.empty(0, np.int64)
    with np.errstate(over="ignore"):
        pair = mix(h[1:] + h[:-1] * np.uint64(0x9E3779B97F4A7C15))
    start = np.ones(len(h), bool)
    start[2:] = pair[:-1] % np.uint64(CHUNK) == 0
    start[1:2] = False
    start[1:] |= doc[1:] != doc[:-1]
    first = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
    second = first + 1
    second = second[second < len(h)]
    start[second[doc[second] == doc[second - 1]]] = False  # its pair would begin in the text before
    return np.flatnonzero(start)


def chunk_hashes(h: np.ndarray, start: np.ndarray) -> np.ndarray:
    """A hash of the words of each chunk, in order."""
    if not len(start):
        return np.empty(0, np.uint64)
    size = np.diff(np.append(start, len(h)))
    place = np.arange(len(h)) - np.repeat(start, size)
    with np.errstate(over="ignore"):
        return mix(np.add.reduceat(mix(h + place.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), start) + size.astype(np.uint64))


class SuffixAutomaton:
    """Suffix automaton of a sequence of word numbers; a state's first transition lies in flat lists, further ones in a dictionary."""

    def __init__(self, text: list[int]):
        most = 2 * len(text) + 2
        self.symbol, self.to = [-1] * most, [0] * most
        self.more: dict[int, dict[int, int]] = {}
        self.link, self.length = [-1] * most, [0] * most
        symbol, goal, more, link, length = self.symbol, self.to, self.more, self.link, self.length
        size, last = 1, 0
        for c in text:
            cur = size
            size += 1
            length[cur] = length[last] + 1
            p = last
            q = -1
            while p >= 0:
                x = symbol[p]
                if x == -1:
                    symbol[p], goal[p] = c, cur
                elif x == c:
                    q = goal[p]
                    break
                else:
                    m = more.get(p)
                    if m is None:
                        more[p] = {c: cur}
                    elif c in m:
                        q = m[c]
                        break
                    else:
                        m[c] = cur
                p = link[p]
            if p < 0:
                link[cur] = 0
            elif length[p] + 1 == length[q]:
                link[cur] = q
            else:
                clone = size
                size += 1
                length[clone] = length[p] + 1
                symbol[clone], goal[clone], link[clone] = symbol[q], goal[q], link[q]
                if q in more:
                    more[clone] = dict(more[q])
                while p >= 0:
                    if symbol[p] == c:
                        if goal[p] != q:
                            break
                        goal[p] = clone
                    else:
                        m = more.get(p)
                        if m is None or m.get(c) != q:
                            break
                        m[c] = clone
                    p = link[p]
                link[q] = link[cur] = clone
            last = cur

    def match_starts(self, z: list[int]) -> list[int]:
        """For each place of z where the longest match that ends there begins; one behind the place where its word is unknown. Rises."""
        symbol, goal, more, link, length = self.symbol, self.to, self.more, self.link, self.length
        state = have = 0
        out = []
        for j, c in enumerate(z, 1):
            while True:
                if symbol[state] == c:
                    state = goal[state]
                    have += 1
                    break
                m = more.get(state)
                if m is not None and c in m:
                    state = m[c]
                    have += 1
                    break
                state = link[state]
                if state < 0:
                    state = have = 0
                    break
                have = length[state]
            out.append(j - have)
        return out


def factor(starts: list[int]) -> int:
    """Number of phrases: each the longest match from where the one before ended, or one unknown word."""
    i = count = 0
    for j, s in enumerate(starts):
        if s > i:
            if j > i:
                count += 1
                i = j
            if s > j:
                count += 1
                i = j + 1
    return count + (i < len(starts))


def own_phrases(z: list[int], width: int) -> int:
    """Phrases of the incremental parsing of z: each is the shortest not seen before."""
    trie: dict[int, int] = {}
    node = count = 0
    for c in z:
        key = node * width + c
        to = trie.get(key)
        if to is None:
            count += 1
            trie[key] = count
            node = 0
        else:
            node = to
    return count + (1 if node else 0)


def repeat_starts(h: np.ndarray, found: list[tuple[int, int, int, int, int]]) -> np.ndarray:
    """Match starts from repeated chunks of a text of word hashes h.

    found has (chunk, document, its chunk, other document, its chunk), either document None for none. A chunk that the
    text itself repeats is told of at its first place only, and counts at all.
    """
    n, start = len(h), chunk_starts(h, np.zeros(len(h), np.int64))
    out = np.arange(1, n + 1)
    edge = np.append(start, n)
    value = chunk_hashes(h, start).tolist()
    at = {value[x[0]]: x[1:] for x in found if x[0] != WHOLE}
    before: dict[tuple[int, int], int] = {}
    for k, v in enumerate(value):
        if v not in at:
            before = {}
            continue
        d1, c1, d2, c2 = at[v]
        now: dict[tuple[int, int], int] = {}
        for d, c in ((d1, c1), (d2, c2)):
            if d is not None:
                now[d, c] = min(before.get((d, c - 1), k), now.get((d, c), k))
        before = now
        out[edge[k] : edge[k + 1]] = start[min(now.values())]
    return out


RESULT = "doc_id long, n_words int, phrases int, own_phrases int, cross_entropy double, divergence double"
CHUNKS = "hash long, key long, chunk int"


def chunks(rows: DataFrame) -> DataFrame:
    """(hash, key, chunk) of the chunks of (key, text), and of each whole text; a hash that a text repeats keeps its first place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, buf, offs in byte_slices(batch):
                h, doc = words(buf, offs)
                start = chunk_starts(h, doc)
                if not len(start):
                    continue
                value, owner = chunk_hashes(h, start), doc[start]
                number = np.arange(len(start)) - np.searchsorted(owner, owner)
                order = np.lexsort((number, value, owner))
                new = np.ones(len(order), bool)
                new[1:] = (value[order][1:] != value[order][:-1]) | (owner[order][1:] != owner[order][:-1])
                keep = order[new]
                have, first = np.unique(doc, return_index=True)
                value, owner, number = np.concatenate([value[keep], mix(chunk_hashes(h, first))]), np.concatenate([owner[keep], have]), np.concatenate([number[keep], np.full(len(have), WHOLE)])
                yield pa.RecordBatch.from_arrays([pa.array(signed(value)), part.column(0).take(pa.array(owner)), pa.array(number.astype(np.int32))], ["hash", "key", "chunk"])

    return rows.select("key", "text").mapInArrow(run, CHUNKS)


def repeated_chunks(every: DataFrame) -> DataFrame:
    """(key, chunk, d1, c1, d2, c2): chunks that another document has too, and one or two places of others."""
    place = F.struct("key", "chunk")
    ends = every.groupBy("hash").agg(F.min(place).alias("a"), F.max(place).alias("b")).where("a.key <> b.key")
    hit = every.join(ends, "hash")
    return hit.select("key", "chunk", *[F.when(F.col(f"{p}.key") != F.col("key"), F.col(f"{p}.{c}")).alias(n) for p, c, n in (("a", "key", "d1"), ("a", "chunk", "c1"), ("b", "key", "d2"), ("b", "chunk", "c2"))])


def _score_shard(table: pa.Table) -> pa.Table:
    is_text = table["repeats"].is_null()
    texts, repeats = table.filter(is_text), table.filter(pa.compute.invert(is_text))
    found: dict[int, np.ndarray] = {}
    for key, raw in zip(repeats["key"].to_pylist(), repeats["repeats"].to_pylist()):
        found[key] = [tuple(x[c] for c in ("chunk", "d1", "c1", "d2", "c2")) for x in raw]
    texts = texts.sort_by([("key", "ascending")]).combine_chunks()
    ids, keys, half = texts["doc_id"].combine_chunks(), texts["key"].to_pylist(), texts["half"].to_numpy()
    batch = pa.RecordBatch.from_arrays([texts["text"].combine_chunks()], ["text"])
    hashes, owners = [], []
    row = 0
    for part, buf, offs in byte_slices(batch):
        h, doc = words(buf, offs)
        hashes.append(h)
        owners.append(doc + row)
        row += part.num_rows
    h, doc = (np.concatenate(x) if x else np.empty(0, t) for x, t in ((hashes, np.uint64), (owners, np.int64)))
    known, code = np.unique(h, return_inverse=True)
    edge = np.searchsorted(doc, np.arange(len(keys) + 1))
    n_words, cross, own = edge[1:] - edge[:-1], np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
    scored = np.zeros(len(keys), bool)
    # equal texts have equal words: they add nothing to a reference, and their own phrases are counted once
    text_of = [h[a:b].tobytes() for a, b in zip(edge[:-1], edge[1:])]
    own_of: dict[bytes, int] = {}
    gc.disable()  # an automaton is millions of small objects without a cycle
    try:
        for side in (0, 1):
            reference: dict[bytes, int] = {}
            for i in np.flatnonzero((half != side) & (n_words > 0)).tolist():
                reference.setdefault(text_of[i], i)
            text: list[int] = []
            for i in reference.values():
                text += code[edge[i] : edge[i + 1]].tolist()
                text.append(len(known) + i)  # a mark of its own ends each text: no match crosses it
            automaton = SuffixAutomaton(text) if text else None
            for i in np.flatnonzero((half == side) & (n_words > 0)).tolist():
                if automaton is None and keys[i] not in found:
                    continue
                z = code[edge[i] : edge[i + 1]].tolist()
                if text_of[i] not in own_of:
                    own_of[text_of[i]] = own_phrases(z, len(known))
                own[i], scored[i] = own_of[text_of[i]], True
                if i and keys[i] == keys[i - 1]:
                    cross[i] = cross[i - 1]
                elif text_of[i] in reference or any(x[0] == WHOLE for x in found.get(keys[i], ())):
                    cross[i] = 1
                else:
                    starts = automaton.match_starts(z) if automaton else list(range(1, len(z) + 1))
                    if keys[i] in found:
                        starts = np.minimum(starts, repeat_starts(h[edge[i] : edge[i + 1]], found[keys[i]])).tolist()
                    cross[i] = factor(starts)
            del automaton, text
    finally:
        gc.enable()
    n = np.maximum(n_words, 1)
    bits = np.where(n > 1, np.log2(np.maximum(n, 2)), 1.0)
    entropy = np.round(cross * bits / n, 6)
    divergence = np.round((cross * bits - own * np.log2(np.maximum(own, 1))) / n, 6)
    null = ~scored
    return pa.table([ids, pa.array(n_words.astype(np.int32)), pa.array(cross.astype(np.int32), mask=null), pa.array(own.astype(np.int32), mask=null), pa.array(entropy, mask=null), pa.array(divergence, mask=null)], ["doc_id", "n_words", "phrases", "own_phrases", "cross_entropy", "divergence"])


def score(docs: DataFrame, shard_bytes: int = SHARD_BYTES, everywhere: bool = True) -> DataFrame:
    """Scores of every row; without ``everywhere`` only the shard's own automata. Languages are few, so their sizes are broadcast."""
    rows = keyed_docs(docs, F.coalesce(F.col("lang").cast("string"), F.lit("")).alias("lang"), F.coalesce(F.octet_length(F.col("text").cast("string")), F.lit(0)).cast("long").alias("bytes"))
    shards = rows.groupBy("lang").agg(F.greatest(F.lit(1), F.ceil(F.sum("bytes") / shard_bytes)).cast("int").alias("shards"))
    deal = F.xxhash64(F.coalesce("doc_id", F.lit(-1)), F.lit("deal"))
    key = F.xxhash64("doc_id", "text").alias("key")
    half = F.pmod(F.floor(deal / F.lit(1 << 20)), F.lit(2)).cast("int").alias("half")
    dealt = rows.join(F.broadcast(shards), "lang").select("lang", F.pmod(F.pmod(deal, F.lit(1 << 20)), F.col("shards")).cast("int").alias("shard"), half, key, "doc_id", "text")
    listed = "array<struct<chunk:int,d1:bigint,c1:int,d2:bigint,c2:int>>"
    placed = dealt.withColumn("repeats", F.lit(None).cast(listed))
    if everywhere:
        # lang and shard follow from the key's row; they ride along with the chunks
        keys = dealt.select("lang", "shard", "key").distinct()
        found = repeated_chunks(stored(chunks(dealt))).groupBy("key").agg(F.collect_list(F.struct("chunk", "d1", "c1", "d2", "c2")).alias("repeats")).join(keys, "key")
        none = lambda c: F.lit(None).cast(placed.schema[c].dataType).alias(c)
        placed = placed.unionByName(found.select("lang", "shard", none("half"), "key", none("doc_id"), none("text"), "repeats"))
    return placed.groupBy("lang", "shard").applyInArrow(_score_shard, RESULT)


def _press(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The words of each text, in lower case with one space between, as compressed bytes with their size."""
    for batch in batches:
        for part, buf, offs in byte_slices(batch):
            low = np.where(IS_WORD[buf], lowered(buf), 32).astype(np.uint8)
            keep = low != 32
            keep[:-1] |= keep[1:]
            at = np.concatenate([[0], np.cumsum(keep)])[offs].tolist()
            low = low[keep].tobytes()
            raw = [low[a:b] for a, b in zip(at, at[1:])]
            yield pa.RecordBatch.from_arrays([*part.columns[:3], pa.array([len(x) for x in raw], pa.int32()), pa.array([pa.compress(x, "zstd", asbytes=True) if x else b"" for x in raw], pa.binary())], ["pack", "doc_id", "key", "size", "words"])


class _Pack:
    """The distinct texts of a pack, one behind the other as word hashes; their order is the same in every step."""

    def __init__(self, docs: pa.Table):
        self.rows: dict[int, list[int | None]] = {}
        packed = {}
        for doc_id, text, size, data in zip(*(docs[c].to_pylist() for c in ("doc_id", "key", "size", "words"))):
            self.rows.setdefault(text, []).append(doc_id)
            packed[text] = data, size
        self.texts = sorted(self.rows)
        raw = [pa.decompress(packed[t][0], packed[t][1], "zstd", asbytes=True) if packed[t][1] else b"" for t in self.texts]
        offs = np.concatenate([[0], np.cumsum([len(x) for x in raw], dtype=np.int64)])
        batch = pa.RecordBatch.from_arrays([pa.LargeStringArray.from_buffers(len(raw), pa.py_buffer(offs), pa.py_buffer(b"".join(raw)))], ["text"])
        hashes, owners, row = [np.empty(0, np.uint64)], [np.empty(0, np.int64)], 0
        for part, buf, at in byte_slices(batch):
            h, doc = words(buf, at)
            hashes.append(h)
            owners.append(doc + row)
            row += part.num_rows
        self.h, self.owner = np.concatenate(hashes), np.concatenate(owners).astype(np.int32)
        self.n = len(self.h)
        self.edge = np.searchsorted(self.owner, np.arange(len(self.texts) + 1))
        size = np.diff(self.edge)
        self.place = np.arange(self.n, dtype=np.int32) - np.repeat(self.edge[:-1], size).astype(np.int32)
        self.left = np.repeat(size, size).astype(np.int32) - self.place
        # documents of each text: equal ids are one
        self.documents = np.array([len(set(self.rows[t])) for t in self.texts], np.int64)
        power, self.inverse = _power_tables(int(size.max(initial=0)) + 1)
        self.run = np.zeros(self.n + 1, np.uint64)
        with np.errstate(over="ignore"):
            np.cumsum(mix(self.h) * power[self.place], out=self.run[1:])

    def grams(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """A hash of the words from each start to each end."""
        with np.errstate(over="ignore"):
            g = self.run[end]
            g -= self.run[start]
            g *= self.inverse[self.place[start]]
            g += (end - start).astype(np.uint64)
            return mix(g)

    def having(self, planes: list[np.ndarray], size: int) -> np.ndarray:
        """Starts of the runs of ``size`` words that may stand in another text: all their shorter runs do, as far as asked."""
        if not planes:
            return np.flatnonzero(self.left >= size).astype(np.int32)
        known = len(planes) + 1
        ok = planes[-1].copy()
        for k in range(1, size - known + 1):
            ok[:-k] &= planes[-1][k:]
            ok[-k:] = False
        return np.flatnonzero(ok).astype(np.int32)

    def branches(self, planes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(start, end, rank, of which start) of the asks of step 5: from every left branching to the next RANKS ends behind the first."""
        shared, left, right = planes[4:7]
        start, stop = np.flatnonzero(left), np.flatnonzero(right)
        begin = shared.copy()
        begin[1:] &= ~(shared[:-1] & (self.owner[1:] == self.owner[:-1]))
        stretch = np.cumsum(begin)
        first, of = np.searchsorted(stop, start), np.arange(len(start))
        out = []
        for r in range(1, RANKS + 1):
            of = of[first[of] + r < len(stop)]
            of = of[stretch[stop[first[of] + r]] == stretch[start[of]]]
            out.append((start[of], stop[first[of] + r] + GRAM, np.full(len(of), r), of))
        return tuple(np.concatenate(x) for x in zip(*out))

    def asks(self, step: int, planes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """(hash, start) of the runs of which a step asks whether another text has them."""
        if step == 5:
            start, end = self.branches(planes)[:2]
        else:
            start = self.having(planes[: step - 1], step + 1)
            end = start + step + 1
        return self.grams(start, end), start


def _distinct(g: np.ndarray) -> np.ndarray:
    """The different hashes, rising; np.unique takes many times as long."""
    s = np.sort(g)
    return s[np.append(np.ones(min(1, len(s)), bool), s[1:] != s[:-1])]


def _groups(g: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Order of the hashes, where in it each distinct one begins, how often it stands there, and the distinct ones."""
    order = np.argsort(g)
    s = g[order]
    first = np.flatnonzero(np.append(np.ones(min(1, len(s)), bool), s[1:] != s[:-1]))
    return order, first, np.diff(first, append=len(s)), s[first]


def _differ(x: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Whether the values of each group differ."""
    return np.minimum.reduceat(x, first) != np.maximum.reduceat(x, first) if len(first) else np.empty(0, bool)


def _spread(value: np.ndarray, order: np.ndarray, count: np.ndarray) -> np.ndarray:
    out = np.empty(len(order), value.dtype)
    out[order] = np.repeat(value, count)
    return out


def _squeeze(u: np.ndarray) -> bytes:
    """Rising hashes as their differences, the like bytes of all compressed together, as the upper ones are small; before them their number and the sizes."""
    packed = [pa.compress(x.tobytes(), "zstd", asbytes=True) for x in np.diff(u, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T]
    return np.array([len(u), *map(len, packed)], np.int32).tobytes() + b"".join(packed)


def _widen(data: bytes) -> tuple[np.ndarray, bytes]:
    """The hashes, and what follows them."""
    n, *size = np.frombuffer(data, np.int32, 9).tolist()
    at = np.cumsum([36, *size]).tolist()
    byte = np.stack([np.frombuffer(pa.decompress(data[a:b], n, "zstd", asbytes=True), np.uint8) for a, b in zip(at, at[1:])], axis=1)
    return np.cumsum(byte.view(np.uint64).ravel(), dtype=np.uint64), data[at[-1] :]


def _bounds(u: np.ndarray, parts: int) -> np.ndarray:
    """Where the rising hashes of each range begin."""
    return np.searchsorted((u >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32), np.arange(parts + 1, dtype=np.uint64))


PLANES = {3: 1, 4: 2, 5: 3, 6: 7}  # of a bit for each word, that a step is told of: has another text the 2, 3, 4, 5, GRAM words here; do the words before, behind differ
MESSAGE = "dest long, kind int, source long, data binary"
STATE, ASKED, ENDS = 0, 1, 2
SIDE = 5  # bytes by which the words before or behind are told apart
ANY = np.uint64(1)  # asked by every pack that has words


def _messages(rows: list[tuple[int, int, int, bytes]]) -> pa.Table:
    dest, kind, source, data = zip(*rows) if rows else ((), (), (), ())
    return pa.table([pa.array(dest, pa.int64()), pa.array(kind, pa.int32()), pa.array(source, pa.int64()), pa.array(data, pa.binary())], ["dest", "kind", "source", "data"])


def _neighbours(pack: _Pack, planes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, tuple, np.ndarray, list[np.ndarray]]:
    """The runs of GRAM words: their starts, distinct hashes, groups, whether two texts of the pack have them, and the one word before and behind (0 where there are several or none)."""
    start = pack.having(planes[:3], GRAM)
    g = pack.grams(start, start + GRAM)
    order, first, count, u = _groups(g)
    at = start[order]
    sides = []
    for word in (np.where(pack.owner[at - 1] == pack.owner[at], pack.h[at - 1], 0) * (at > 0).astype(np.uint64), np.where(pack.left[at] > GRAM, pack.h[np.minimum(at + GRAM, max(pack.n - 1, 0))], 0).astype(np.uint64)):
        sides.append(np.where(_differ(word, first), np.uint64(0), word[first]))
    return start, u, (order, first, count), _differ(pack.owner[at], first), sides


def _step(step: int, parts: int):
    """Step 1 to 6 of a pack: takes in the answers to what the step before asked, and asks further or gives the result."""

    def run(key: tuple, docs: pa.Table, told: pa.Table | None = None) -> pa.Table:
        pack, m = _Pack(docs), key[0].as_py()
        planes: list[np.ndarray] = []
        alone, answers = True, {ASKED: {}, ENDS: {}}
        for kind, source, data in zip(*(told[c].to_pylist() for c in ("kind", "source", "data"))) if told is not None else ():
            if kind == STATE:
                n = -(-pack.n // 8)
                raw = np.frombuffer(pa.decompress(data[1:], n * PLANES[step], "zstd", asbytes=True) if n else b"", np.uint8).reshape(PLANES[step], n)
                alone, planes = bool(data[0]), [np.unpackbits(x, count=pack.n).astype(bool) for x in raw]
            else:
                answers[kind][source] = data

        def heard(kind: int, u: np.ndarray, each: int = 1) -> np.ndarray:
            n = np.diff(_bounds(u, parts))
            out = [np.stack([np.unpackbits(x, count=c) for x in np.frombuffer(answers[kind][p], np.uint8).reshape(each, -1)]) for p, c in enumerate(n.tolist()) if c]
            return np.concatenate(out, axis=1).astype(bool) if out else np.empty((each, 0), bool)

        g = other = None
        if step > 1:
            g, start = pack.asks(step - 1, planes)
            order, first, count, u = _groups(g)
            both = _differ(pack.owner[start][order], first)
            if step == 2 and pack.n:
                at = np.searchsorted(u, ANY)
                told_of = heard(ASKED, np.insert(u, at, ANY))[0]
                alone = not told_of[at] and pack.documents[np.diff(pack.edge) > 0].sum() < 2
                both |= np.delete(told_of, at)
            else:
                both |= heard(ASKED, u)[0]
            other = _spread(both, order, count)
            if step < 6:
                planes.append(np.zeros(pack.n, bool))
                planes[-1][start[other]] = True
            if step == 5:
                begin, u, (order, first, count), both, _ = _neighbours(pack, planes)
                shared, left, right = heard(ENDS, u, 3)
                shared |= both
                for value in (shared, shared & left, shared & right):
                    plane = np.zeros(pack.n, bool)
                    plane[begin] = _spread(value, order, count)
                    planes.append(plane)
        if step == 6:
            return _result(pack, m, planes, alone, g, other)
        rows = []
        if step > 1:
            del g, start, order, first, count, u, both, other
            state = b"".join(np.packbits(x).tobytes() for x in planes)
            rows.append((-1 - m, STATE, m, bytes([int(alone)]) + (pa.compress(state, "zstd", asbytes=True) if state else b"")))
        u = _distinct(pack.asks(step, planes)[0])
        if step == 1 and pack.n:
            u = np.insert(u, np.searchsorted(u, ANY), ANY)
        edge = _bounds(u, parts).tolist()
        rows += [(p, ASKED, m, _squeeze(u[a:b])) for p, (a, b) in enumerate(zip(edge, edge[1:])) if a < b]
        if step == 4:
            _, u, _, _, sides = _neighbours(pack, planes)
            edge = _bounds(u, parts).tolist()
            rows += [(p, ENDS, m, b"".join([_squeeze(u[a:b]), *[x[a:b].view(np.uint8).reshape(-1, 8)[:, :SIDE].tobytes() for x in sides]])) for p, (a, b) in enumerate(zip(edge, edge[1:])) if a < b]
        return _messages(rows)

    def lean(*given) -> pa.Table:
        out = run(*given)
        pa.default_memory_pool().release_unused()
        return out

    return (lambda key, docs: lean(key, docs)) if step == 1 else (lambda key, docs, told: lean(key, docs, told))


def _answer(table: pa.Table) -> pa.Table:
    """Tells each pack which of its hashes of a range another pack has too, and of runs of GRAM words, whether the words before or behind differ."""
    rows = []
    kinds, sources, blobs = (table[c].to_pylist() for c in ("kind", "source", "data"))
    rows += [(s, STATE, s, x) for k, s, x in zip(kinds, sources, blobs) if k == STATE]
    for kind in (ASKED, ENDS):
        here = [(s, *_widen(x)) for k, s, x in zip(kinds, sources, blobs) if k == kind]
        if not here:
            continue
        size = [len(u) for _, u, _ in here]
        order, first, count, _ = _groups(np.concatenate([u for _, u, _ in here]))
        tell = [_spread(count > 1, order, count)]
        for side in range(2 if kind == ENDS else 0):
            byte = np.concatenate([np.frombuffer(x, np.uint8, SIDE * n, SIDE * n * side).reshape(n, SIDE) for (_, _, x), n in zip(here, size)])
            word = np.pad(byte, ((0, 0), (0, 8 - SIDE))).view(np.uint64).ravel()[order]
            tell.append(_spread(_differ(word, first) | (word[first] == 0), order, count))
        at = np.concatenate([[0], np.cumsum(size)]).tolist()
        rows += [(s, kind, table["dest"][0].as_py(), b"".join(np.packbits(x[a:b]).tobytes() for x in tell)) for (s, _, _), a, b in zip(here, at, at[1:])]
    return _messages(rows)


FOUND = "doc_id long, n_words int, phrases int, own_phrases int, node long, hashes binary, reach binary, grams array<long>, links array<long>"


def parse(reach: list[int]) -> int:
    """Number of phrases, given how long a match begins at each word."""
    i = count = 0
    while i < len(reach):
        i += reach[i] or 1
        count += 1
    return count


def _result(pack: _Pack, m: int, planes: list[np.ndarray], alone: bool, g: np.ndarray, other: np.ndarray) -> pa.Table:
    """A row for each document, and one with its words for each text with a match beyond RANKS ends."""
    reach = np.zeros(pack.n, np.int64)
    for size, plane in zip((2, 3, 4, 5), planes):
        reach[plane] = size
    shared, left, right = planes[4:7]
    begin, stop = np.flatnonzero(left), np.flatnonzero(right)
    _, end, rank, of = pack.branches(planes)
    if len(begin):  # the first end behind a start is reached by all that have the start
        best = stop[np.searchsorted(stop, begin)] + GRAM
        np.maximum.at(best, of[other], end[other])
        inside = np.flatnonzero(shared)
        reach[inside] = best[np.searchsorted(begin, inside, side="right") - 1] - inside
    beyond = np.flatnonzero(other & (rank == RANKS))
    text = pack.owner[begin[of[beyond]]]
    order, first, count, gram = _groups(g[beyond])
    lead = np.minimum.reduceat(text[order], first) if len(first) else np.empty(0, np.int64)
    gram = signed(gram)[np.argsort(lead, kind="stable")]
    cuts = np.searchsorted(np.sort(lead), np.arange(len(pack.texts) + 1))
    links: dict[int, list[int]] = {t: [] for t in np.unique(text).tolist()}
    for x in np.unique(text * len(pack.texts) + _spread(lead, order, count)).tolist():
        t, to = divmod(x, len(pack.texts))
        if t != to:
            links[t].append((m << 32) + to)
    out = []
    edge = pack.edge.tolist()
    for t, text in enumerate(pack.texts):
        a, b = edge[t], edge[t + 1]
        phrases = own = None
        node = (m << 32) + t
        if b > a and not alone:
            own = own_phrases(np.unique(pack.h[a:b], return_inverse=True)[1].tolist(), b - a)
            phrases = 1 if pack.documents[t] > 1 else None if t in links else parse(reach[a:b].tolist())
        out += [(doc_id, b - a, phrases, own, node, None, None, None, None) for doc_id in pack.rows[text]]
        if t in links:
            out.append((None, None, None, None, node, pack.h[a:b].tobytes(), reach[a:b].astype(np.int32).tobytes(), gram[cuts[t] : cuts[t + 1]].tolist(), links[t]))
    names = [x.split()[0] for x in FOUND.split(", ")]
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int64())]
    return pa.table([pa.array(x, k) for x, k in zip(zip(*out) if out else [()] * len(names), kinds)], names=names)


def other_reach(z: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """How long the longest match with another text is that begins at each word. z has the words of all texts, doc rises.

    Names of runs of 1, 2, 4, ... words in their order; the last sorts all that begins anywhere, and next to a place in that order stand those most like it.
    """
    n = len(z)
    if not n:
        return np.zeros(0, np.int32)
    last = np.append(doc[1:] != doc[:-1], True)
    at = np.arange(n) + np.cumsum(last) - last  # each text is followed by a mark of its own
    total = n + int(last.sum())
    name = np.empty(total, np.int64)
    known, name[at] = np.unique(z, return_inverse=True)
    name[at[last] + 1] = len(known) + np.arange(last.sum())
    levels, size = [name.astype(np.int32)], 1
    while True:
        pair = levels[-1] * np.int64(total + 2)
        pair[:-size] += levels[-1][size:] + 1
        order, first, count, _ = _groups(pair.view(np.uint64))
        levels.append(_spread(np.arange(len(first)), order, count).astype(np.int32))
        size *= 2
        if len(first) == total or size >= total:
            break
    del name, pair, first, count
    text = np.empty(total, np.int32)
    text[at] = doc
    text[at[last] + 1] = doc[last]
    best = np.zeros(total, np.int32)
    order = order.astype(np.int32)
    for line in (order, order[::-1]):
        new = np.append(True, np.diff(text[line]) != 0)
        before = np.maximum.accumulate(np.where(new, np.arange(total, dtype=np.int32), 0)) - 1
        mine, its = line[before >= 0], line[before[before >= 0]]
        have = np.zeros(len(mine), np.int32)
        for k in range(len(levels) - 1, -1, -1):
            # marks are all different, so a match never goes beyond the end
            x, y = np.minimum(mine + have, total - 1), np.minimum(its + have, total - 1)
            have += (levels[k][x] == levels[k][y]) * np.int32(1 << k)
        best[mine] = np.maximum(best[mine], have)
    return best[at]


def _meet(table: pa.Table) -> pa.Table:
    """The reach of the texts of a bin among themselves, no less than it was known to be."""
    nodes = table["node"].to_pylist()
    hashes = [np.frombuffer(x, np.uint64) for x in table["hashes"].to_pylist()]
    doc = np.repeat(np.arange(len(nodes)), [len(x) for x in hashes])
    reach = other_reach(np.concatenate(hashes), doc)
    at = np.concatenate([[0], np.cumsum([len(x) for x in hashes])]).tolist()
    known = [np.frombuffer(x, np.int32) for x in table["reach"].to_pylist()]
    return pa.table([table["node"], pa.array([np.maximum(x, reach[a:b]).astype(np.int32).tobytes() for x, a, b in zip(known, at, at[1:])], pa.binary())], ["node", "reach"])


def _parse_all(table: pa.Table) -> pa.Table:
    best: dict[int, np.ndarray] = {}
    for node, raw in zip(table["node"].to_pylist(), table["reach"].to_pylist()):
        x = np.frombuffer(raw, np.int32)
        best[node] = np.maximum(best[node], x) if node in best else x
    return pa.table([pa.array(best, pa.int64()), pa.array([parse(x.tolist()) for x in best.values()], pa.int32())], ["node", "far_phrases"])


def score_whole(docs: DataFrame, part_bytes: int = PACK_BYTES) -> DataFrame:
    """Scores of every row against all other documents of the corpus, with no match missed. Null are the scores of a text without words, or where no other has words."""
    rows = keyed_docs(docs).withColumn("text", F.coalesce("text", F.lit("")))
    parts = max(1, -(-(rows.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0) // part_bytes))
    packs = rows.select(F.pmod(F.xxhash64("text"), F.lit(parts).cast("long")).alias("pack"), "doc_id", F.xxhash64("text").alias("key"), "text").mapInArrow(_press, "pack long, doc_id long, key long, size int, words binary").groupBy("pack")
    asked = packs.applyInArrow(_step(1, parts), MESSAGE)
    for step in range(2, 7):
        answers = asked.groupBy("dest").applyInArrow(_answer, MESSAGE)
        asked = packs.cogroup(answers.groupBy("dest")).applyInArrow(_step(step, parts), FOUND if step == 6 else MESSAGE)
    found = stored(asked)
    result, texts = found.where("hashes is null"), found.where("hashes is not null")
    n_bytes = texts.agg(F.sum(F.length("hashes").cast("long"))).first()[0] or 0
    if n_bytes:
        result = result.join(_far_phrases(texts, n_bytes, part_bytes // 5), "node", "left").withColumn("phrases", F.coalesce("phrases", "far_phrases"))
    bits = F.when(F.col("n_words") > 1, F.log2("n_words")).otherwise(1.0)
    cross = F.col("phrases") * bits
    own = F.col("own_phrases") * F.log2(F.greatest("own_phrases", F.lit(1)))
    return result.select("doc_id", "n_words", "phrases", "own_phrases", F.bround(cross / F.col("n_words"), 6).alias("cross_entropy"), F.bround((cross - own) / F.col("n_words"), 6).alias("divergence"))


def _far_phrases(texts: DataFrame, n_bytes: int, block_bytes: int) -> DataFrame:
    """(node, far_phrases) of the texts with matches beyond RANKS ends: those that such matches join, directly or through others, meet in a bin, and
    in a bin larger than two blocks every two blocks meet."""
    grams = texts.select("node", F.explode("grams").alias("gram"))
    least = grams.groupBy("gram").agg(F.min("node").alias("to"))
    edges = grams.join(least, "gram").where("node <> to").select("node", "to").unionByName(texts.select("node", F.explode("links").alias("to")))
    roots = components(edges.select(F.col("node").alias("doc_id_a"), F.col("to").alias("doc_id_b"))).withColumnRenamed("doc_id", "node")
    bins = -(-n_bytes // block_bytes)
    placed = texts.select("node", "hashes", "reach").join(roots, "node", "left").select("node", "hashes", "reach", F.pmod(F.xxhash64(F.coalesce("root", "node")), F.lit(bins).cast("long")).alias("bin"))
    sizes = placed.groupBy("bin").agg(F.sum(F.length("hashes").cast("long")).alias("n")).select("bin", F.when(F.col("n") <= 2 * block_bytes, 1).otherwise(F.ceil(F.col("n") / block_bytes)).cast("int").alias("blocks"))
    dealt = placed.join(sizes, "bin").withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).where("blocks = 1 or own <> other")
    met = dealt.select("bin", "node", "hashes", "reach", F.least("own", "other").alias("t"), F.greatest("own", "other").alias("r")).repartition(2 * bins, "bin", "t", "r").groupBy("bin", "t", "r").applyInArrow(_meet, "node long, reach binary")
    return met.groupBy(F.pmod(F.xxhash64("node"), F.lit(bins).cast("long"))).applyInArrow(_parse_all, "node long, far_phrases int")


def op4_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_whole(load(spark, sf_dir, "documents"))
