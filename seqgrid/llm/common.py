"""Shared helpers: byte views of Arrow text columns, word hashing, checkpoint folder, name-safe input.

All text work below runs on the UTF-8 bytes of a whole Arrow batch at once, in slices of about
``SLICE_BYTES`` so that temporary numpy arrays stay far below an executor's memory; a longer text is one
slice of its own and is still processed whole.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 1 << 18
DOC_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")

_POLY = 0x9E3779B97F4A7C15 | 1
_POLY_INV = pow(_POLY, -1, 1 << 64)
_U64 = np.uint64

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
IS_WORD = np.zeros(256, dtype=bool)
IS_WORD[48:58] = IS_WORD[65:91] = IS_WORD[97:123] = IS_WORD[128:] = True
IS_LETTER = IS_WORD.copy()
IS_LETTER[48:58] = False
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where the session names none and runs on this machine alone (tests)."""
    sc = spark.sparkContext
    have = sc._jsc.sc().getCheckpointDir()
    if have.isDefined():
        return have.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and (not sc.master.startswith("local") or sc.master.startswith("local-cluster")):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="seqgrid-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage in the folder that all executors share."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """df written as Parquet in the folder that all executors share, and read again: for tables that several jobs read, smaller than a checkpoint."""
    path = f"{shared_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def keyed_docs(docs: DataFrame, *extra: str) -> DataFrame:
    """Only the named columns: further columns of the caller, whatever their names, can't clash."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *extra)


def byte_slices(batch: pa.RecordBatch, column: str = "text", most: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(rows, uint8 bytes, int64 offsets) of consecutive row ranges; a null text has no bytes."""
    n = batch.num_rows
    if not n:
        return
    arr = batch.column(batch.schema.get_field_index(column))
    if arr.null_count:
        arr = arr.fill_null("")
    arr = arr.cast(pa.large_string()) if not pa.types.is_large_string(arr.type) else arr
    offs = np.frombuffer(arr.buffers()[1], dtype=np.int64)[arr.offset : arr.offset + n + 1]
    data = np.frombuffer(arr.buffers()[2], dtype=np.uint8) if arr.buffers()[2] is not None else np.empty(0, np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + most, side="right")) - 1)
        hi = min(hi, n)
        yield batch.slice(lo, hi - lo), data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
        lo = hi


def lowered(buf: np.ndarray) -> np.ndarray:
    """Lower case of ASCII and of the two-byte Latin-1 letters; other letters as they are."""
    low = LOWER[buf]
    lead = np.flatnonzero(buf[:-1] == 0xC3) + 1
    follow = low[lead]
    low[lead] = np.where((follow >= 0x80) & (follow <= 0x9E) & (follow != 0x97), follow + 0x20, follow)
    return low


_powers: list[np.ndarray] = [np.ones(1, _U64), np.ones(1, _U64)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, SLICE_BYTES + 1024)
        for k, base in enumerate((_POLY, _POLY_INV)):
            with np.errstate(over="ignore"):
                table = np.full(size, base, _U64)
                table[0] = 1
                _powers[k] = np.cumprod(table, dtype=_U64)
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A finalizer, so that every bit of the result depends on every bit of h."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> _U64(30))) * _U64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> _U64(27))) * _U64(0x94D049BB133111EB)
        return h ^ (h >> _U64(31))


def spans(buf: np.ndarray, offs: np.ndarray, member: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of bytes for which member[byte], never across texts."""
    if not len(buf):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    inside = member[buf]
    edge = np.empty(len(buf) + 1, bool)
    edge[0], edge[-1] = True, True
    edge[1:-1] = inside[1:] != inside[:-1]
    edge[offs] = True
    at = np.flatnonzero(edge)
    good = inside[at[:-1]]
    return at[:-1][good], at[1:][good]


def word_table(buf: np.ndarray, offs: np.ndarray, member: np.ndarray = IS_WORD) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, 64-bit hash of the lower-cased word, index of its text) of every word."""
    start, end = spans(buf, offs, member)
    if not len(start):
        return start, end, np.empty(0, _U64), np.empty(0, np.int64)
    pw, inv = _power_tables(len(buf) + 1)
    with np.errstate(over="ignore"):
        run = np.zeros(len(buf) + 1, _U64)
        np.cumsum((lowered(buf).astype(_U64) + _U64(1)) * pw[: len(buf)], out=run[1:])
        h = mix((run[end] - run[start]) * inv[start] + (end - start).astype(_U64))
    return start, end, h, np.searchsorted(offs, start, side="right") - 1


def word_hash(word: str) -> int:
    """The hash that word_table gives this word."""
    raw = np.frombuffer(word.encode(), np.uint8)
    return int(word_table(raw, np.array([0, len(raw)]), np.ones(256, bool))[2][0])


def shingle_table(h: np.ndarray, doc: np.ndarray, n_docs: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash of the distinct word n-grams, offsets by text); a text of 1 to width-1 words has one shorter n-gram."""
    counts = np.bincount(doc, minlength=n_docs)
    first = np.concatenate([[0], np.cumsum(counts)])
    if not len(h):
        return np.empty(0, _U64), np.zeros(n_docs + 1, np.int64)
    with np.errstate(over="ignore"):
        gram = h.copy()
        left = np.repeat(first[1:], counts) - np.arange(len(h))  # words left in the text, this one included
        for k in range(1, width):
            nxt = np.zeros_like(h)
            nxt[:-k] = h[k:]
            gram = gram * _U64(0xD6E8FEB86659FD93) + np.where(left > k, nxt, _U64(0))
        gram = mix(gram)
    keep = (left >= width) | ((np.arange(len(h)) == np.repeat(first[:-1], counts)))
    gram, owner = gram[keep], doc[keep]
    order = np.lexsort((gram, owner))
    gram, owner = gram[order], owner[order]
    new = np.ones(len(gram), bool)
    new[1:] = (gram[1:] != gram[:-1]) | (owner[1:] != owner[:-1])
    gram, owner = gram[new], owner[new]
    return gram, np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=n_docs))])


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)
