"""Operator 9, quality classifier: a byte-level convolutional network in numpy.

Six-byte filters slide over the raw UTF-8 bytes in steps of two. Overlapping chunks of 512 bytes, 256 apart,
cover the whole text; each chunk keeps the maximum of every filter (max pooling), and the mean and the maximum
of the rectified chunk values over all chunks feed one logistic output: ``p_quality``.

The good class is quality 1 without the label toxic; a document labelled toxic is a reject whatever its quality.
Training uses at most ``train_per_class`` labelled documents of each class (the documented bound), taken by
least hash of the id, in one executor task, for 14 epochs but at least 300 updates (small samples need more
epochs); nothing of it depends on the size of the corpus. Scoring is one
map over the documents: no shuffle. Because a filter starts at even offsets only, two neighbouring taps fold
into one table of 65536 byte pairs, so a filter bank costs three look-ups for two bytes.

Defined results: null or empty text scores 0 and is rejected. Without labelled documents, or with one class
only, every other text scores the smoothed share of good labels (0.5 without labels) and is kept from 0.5 on.
A document labelled both good and not, or toxic in any row, is a reject. Repeated rows score alike; further columns are ignored by score() and kept by keep_good().
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import byte_slices, keyed_docs, load

TAPS, FILTERS, CHUNK, STEP = 6, 16, 256, 128  # CHUNK and STEP count filter positions, two bytes each
TRAIN_PER_CLASS = 1500


def _padded(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Texts at even offsets, zero bytes between them; offsets in byte pairs."""
    length = np.diff(offs)
    room = (length + 1) // 2 * 2 + TAPS
    at = np.concatenate([[0], np.cumsum(room)])
    out = np.zeros(int(at[-1]), np.uint8)
    out[np.arange(len(buf)) + np.repeat(at[:-1] - offs[:-1], length)] = buf
    return out, at // 2


def _chunk_starts(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the half chunks of all texts, and how many each text has."""
    positions = np.maximum(np.diff(at) - TAPS // 2, 1)
    halves = -(-positions // STEP)
    first = np.concatenate([[0], np.cumsum(halves)])
    return np.repeat(at[:-1], halves) + (np.arange(first[-1]) - np.repeat(first[:-1], halves)) * STEP, halves


class ByteCNN:
    def __init__(self, w: np.ndarray, b: np.ndarray, v: np.ndarray, c: float, prior: float | None = None):
        self.w, self.b, self.v, self.c, self.prior, self._tables = w, b, v, c, prior, None

    def dump(self) -> bytes:
        f = io.BytesIO()
        np.savez(f, w=self.w, b=self.b, v=self.v, c=np.float32(self.c), prior=np.float64(-1 if self.prior is None else self.prior))
        return f.getvalue()

    @staticmethod
    def load(raw: bytes) -> ByteCNN:
        z = np.load(io.BytesIO(raw))
        return ByteCNN(z["w"], z["b"], z["v"], float(z["c"]), None if z["prior"] < 0 else float(z["prior"]))

    @staticmethod
    def constant(prior: float) -> ByteCNN:
        z = np.zeros
        return ByteCNN(z((TAPS, 256, 1), np.float32), z(1, np.float32), z(2, np.float32), 0.0, prior)

    def features(self, buf: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """Mean and maximum over a text's chunks of the pooled, rectified filters."""
        if self._tables is None:
            self._tables = [(self.w[k][None, :, :] + self.w[k + 1][:, None, :]).reshape(65536, -1) for k in range(0, TAPS, 2)]  # little endian pairs
        padded, at = _padded(buf, offs)
        pairs = np.concatenate([padded.view("<u2"), np.zeros(TAPS // 2, "<u2")])
        n = int(at[-1])
        z = self._tables[0][pairs[:n]]
        for k in range(1, TAPS // 2):
            z += self._tables[k][pairs[k : n + k]]
        z[at[1:] - 1] = z[at[1:] - 2] = -np.inf  # these would look into the next text
        starts, halves = _chunk_starts(at)
        top = np.maximum.reduceat(z, starts, axis=0)
        last = np.cumsum(halves) - 1
        chunk = top.copy()
        chunk[:-1] = np.maximum(top[:-1], top[1:])
        chunk[last] = top[last]
        # the last half chunk is part of the chunk before it, unless it is the only one
        alone = np.ones(len(chunk), bool)
        alone[last[halves > 1]] = False
        owner = np.repeat(np.arange(len(halves)), halves)[alone]
        r = np.maximum(chunk[alone] + self.b, 0)
        first = np.searchsorted(owner, np.arange(len(halves)))
        return np.concatenate([np.add.reduceat(r, first, axis=0) / np.maximum(halves - 1, 1)[:, None], np.maximum.reduceat(r, first, axis=0)], axis=1)

    def predict(self, buf: np.ndarray, offs: np.ndarray) -> np.ndarray:
        if self.prior is not None:
            p = np.full(len(offs) - 1, self.prior)
        else:
            p = 1 / (1 + np.exp(-np.clip(self.features(buf, offs) @ self.v + self.c, -30, 30).astype(np.float64)))
        p[np.diff(offs) == 0] = 0.0
        return p


def fit(texts: list[bytes], labels: np.ndarray, epochs: int = 14, seed: int = 7, batch: int = 32, updates: int = 300) -> ByteCNN:
    """Adam on the cross entropy, in at least so many epochs and updates; both classes weigh the same; gradients go through the maxima only."""
    y = np.asarray(labels, np.float32)
    if not len(y) or y.min() == y.max():
        return ByteCNN.constant(float((y.sum() + 1) / (len(y) + 2)))
    epochs = max(epochs, -(-updates // -(-len(texts) // batch)))
    rng = np.random.default_rng(seed)
    par = [rng.normal(0, 0.15, (TAPS, 256, FILTERS)).astype(np.float32), np.zeros(FILTERS, np.float32), rng.normal(0, 0.1, 2 * FILTERS).astype(np.float32), np.zeros(1, np.float32)]
    m1, m2, t = [np.zeros_like(p) for p in par], [np.zeros_like(p) for p in par], 0
    weight = np.where(y > 0, 0.5 / y.mean(), 0.5 / (1 - y.mean())).astype(np.float32)
    raw = [np.frombuffer(x, np.uint8) for x in texts]
    for epoch in range(epochs):
        order = rng.permutation(len(raw))
        rate = 0.01 if epoch < epochs * 2 // 3 else 0.002
        for lo in range(0, len(order), batch):
            ids = order[lo : lo + batch]
            n_chunks = [max(1, -(-(len(raw[i]) + 1) // 2 // STEP)) for i in ids]
            n_chunks = [max(1, n - 1) for n in n_chunks]
            owner = np.repeat(np.arange(len(ids)), n_chunks)
            first = np.concatenate([[0], np.cumsum(n_chunks)])[:-1]
            view = np.zeros((len(owner), CHUNK * 2 + TAPS), np.uint8)
            row = 0
            for i, n in zip(ids, n_chunks):
                for k in range(n):
                    piece = raw[i][k * STEP * 2 : k * STEP * 2 + CHUNK * 2 + TAPS]
                    view[row, : len(piece)] = piece
                    row += 1
            w, b, v, c = par
            z = w[0][view[:, 0 : 2 * CHUNK : 2]]
            for k in range(1, TAPS):
                z += w[k][view[:, k : k + 2 * CHUNK : 2]]
            arg = z.argmax(1)
            top = np.take_along_axis(z, arg[:, None, :], 1)[:, 0] + b
            r = np.maximum(top, 0)
            mean = np.add.reduceat(r, first, axis=0) / np.array(n_chunks)[:, None]
            most = np.maximum.reduceat(r, first, axis=0)
            p = 1 / (1 + np.exp(-np.clip(np.concatenate([mean, most], 1) @ v + c, -30, 30)))
            g = ((p - y[ids]) * weight[ids] / len(ids)).astype(np.float32)
            gr = (g[:, None] * v[:FILTERS])[owner] / np.array(n_chunks, np.float32)[owner][:, None]
            gr += np.where(r == most[owner], (g[:, None] * v[FILTERS:])[owner], 0)
            gr *= top > 0
            gw = np.zeros_like(w)
            f = np.broadcast_to(np.arange(FILTERS), arg.shape)
            for k in range(TAPS):
                np.add.at(gw[k], (np.take_along_axis(view, arg * 2 + k, 1), f), gr)
            grads = [gw, gr.sum(0), np.concatenate([g @ mean, g @ most]) + 1e-4 * v, np.array([g.sum()])]
            t += 1
            for q in range(4):
                m1[q] = 0.9 * m1[q] + 0.1 * grads[q]
                m2[q] = 0.999 * m2[q] + 0.001 * grads[q] ** 2
                par[q] = (par[q] - rate * (m1[q] / (1 - 0.9**t)) / (np.sqrt(m2[q] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
    return ByteCNN(par[0], par[1], par[2], float(par[3][0]))


def train(docs: DataFrame, labels: DataFrame, train_per_class: int = TRAIN_PER_CLASS) -> ByteCNN:
    """Fit on a sample of at most 2 x train_per_class labelled documents; the ids are broadcast, and bounded."""
    toxic = F.coalesce(F.col("toxic").cast("int"), F.lit(0)) if "toxic" in labels.columns else F.lit(0)
    lab = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.when(toxic == 1, 0).otherwise(F.col("quality").cast("int")).alias("good")).where("doc_id is not null and good in (0, 1)").groupBy("doc_id").agg(F.min("good").alias("good"))
    pick = [lab.where(F.col("good") == q).orderBy(F.xxhash64("doc_id"), "doc_id").limit(train_per_class) for q in (0, 1)]
    sample = keyed_docs(docs).where("length(text) > 0").join(F.broadcast(pick[0].unionByName(pick[1])), "doc_id")

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["doc_id", "text"]).drop_duplicates("doc_id")
        return pd.DataFrame({"model": [fit([t.encode() for t in pdf["text"]], pdf["good"].to_numpy()).dump()]})

    rows = sample.groupBy(F.lit(0).alias("all")).applyInPandas(task, "model binary").collect()
    return ByteCNN.load(rows[0]["model"]) if rows else ByteCNN.constant(0.5)


def _batch_scores(net: ByteCNN, batch: pa.RecordBatch) -> np.ndarray:
    """Slices small enough for their filter responses to stay in the processor's cache."""
    return np.concatenate([net.predict(buf, offs) for _, buf, offs in byte_slices(batch, most=1 << 17)])


def score(docs: DataFrame, model: ByteCNN, threshold: float = 0.5) -> DataFrame:
    """(doc_id, p_quality, accepted) of every row of docs."""
    raw = model.dump()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = ByteCNN.load(raw)
        for batch in batches:
            if batch.num_rows:
                p = _batch_scores(net, batch)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.round(p, 6)), pa.array(p >= threshold)], ["doc_id", "p_quality", "accepted"])

    return keyed_docs(docs).mapInArrow(run, "doc_id long, p_quality double, accepted boolean")


def keep_good(docs: DataFrame, model: ByteCNN, threshold: float = 0.5) -> DataFrame:
    """The rows of docs, all columns, that the network accepts."""
    raw, schema = model.dump(), docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = ByteCNN.load(raw)
        for batch in batches:
            if batch.num_rows:
                yield batch.filter(pa.array(_batch_scores(net, batch) >= threshold))

    return docs.mapInArrow(run, schema)


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return score(docs, train(docs, load(spark, sf_dir, "labels")))
