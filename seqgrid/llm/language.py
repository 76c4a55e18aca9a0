"""Operator 2, language identification of multilingual mixtures by expectation-maximisation.

Every language has a byte-trigram model over lower-cased text. A word has one language; its likelihood under a
language is the product of its trigrams' (the word with one separator on each side). A document's proportions
are fitted by expectation-maximisation over its words, for a shrinking set of languages: after each fit the
weakest language leaves, and of all sets the one with the greatest penalised log likelihood
(``PENALTY`` * log(words) for each language beyond the first) is kept.

Models are counted on at most about ``train_docs_per_lang`` documents of each declared language (the documented
bound), taken by a hash of the id; they have a fixed size, TRIGRAMS floats for each language. Everything else is
one map over whole texts, without a shuffle.

Defined results: a text without letters (null and empty included) is 'und', with empty lists, and not accepted.
Rows with a null ``lang`` are not trained on; with no trainable language every text is 'und'. A document is accepted when its largest
share is at least ``min_share`` and the mean log likelihood of its trigrams under the mixture is not below the
floor of that language (the mean of the language's own model minus FLOOR_SD standard deviations). Repeated rows get equal results.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import IS_LETTER, byte_slices, keyed_docs, load, lowered, spans

TRIGRAMS = 1 << 16
TRAIN_DOCS_PER_LANG = 1000
PENALTY, MIN_SHARE, FLOOR_SD, ROUNDS = 2.0, 0.5, 2.0, 6


def _word_codes(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Trigram code around every letter byte; first code of each word; text of each word."""
    start, end = spans(buf, offs, IS_LETTER)
    if not len(start):
        return np.empty(0, np.int64), start, start
    x = np.where(IS_LETTER[buf], lowered(buf), 32).astype(np.uint32)
    padded = np.concatenate([[np.uint32(32)], x, [np.uint32(32)]]).astype(np.uint32)
    left, right = padded[:-2].copy(), padded[2:].copy()
    left[offs[:-1][offs[:-1] < len(buf)]] = 32  # no trigram crosses from text to text
    right[offs[1:][offs[1:] > 0] - 1] = 32
    with np.errstate(over="ignore"):
        code = ((((left << np.uint32(16)) | (x << np.uint32(8)) | right) * np.uint32(2654435761)) >> np.uint32(16)).astype(np.int64)
    inside = IS_LETTER[buf]
    length = end - start
    return code[inside], np.concatenate([[0], np.cumsum(length)[:-1]]), np.searchsorted(offs, start, side="right") - 1


class LanguageModel:
    def __init__(self, langs: list[str], logp: np.ndarray, floors: np.ndarray):
        self.langs, self.logp, self.floors = langs, np.ascontiguousarray(logp, np.float32), floors

    def dump(self) -> bytes:
        f = io.BytesIO()
        np.savez(f, langs=np.array(self.langs, dtype=str), logp=self.logp, floors=self.floors)
        return f.getvalue()

    @staticmethod
    def load(raw: bytes) -> LanguageModel:
        z = np.load(io.BytesIO(raw))
        return LanguageModel([str(x) for x in z["langs"]], z["logp"], z["floors"])

    def infer(self, buf: np.ndarray, offs: np.ndarray, penalty: float = PENALTY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(proportions, zero outside the selected set; mean trigram log likelihood under that mixture; words) of each text."""
        n, k = len(offs) - 1, len(self.langs)
        share, fit, words = np.zeros((n, k)), np.full(n, -np.inf), np.zeros(n, np.int64)
        code, first, doc = _word_codes(buf, offs)
        if not len(doc) or not k:
            return share, fit, words
        ll = np.add.reduceat(self.logp[code], first, axis=0)
        words = np.bincount(doc, minlength=n)
        have = np.flatnonzero(words)
        row = np.cumsum(words[have]) - words[have]  # first word of each text that has any
        own = np.repeat(np.arange(len(have)), words[have])
        letters = np.add.reduceat(np.diff(np.append(first, len(code))), row)
        top = ll.max(1)
        like = np.exp(ll - top[:, None])
        base = np.add.reduceat(top.astype(np.float64), row)
        count = words[have].astype(np.float64)
        active = np.ones((len(have), k), bool)
        best = np.full(len(have), -np.inf)
        best_pi, best_fit = np.zeros((len(have), k)), np.zeros(len(have))
        pi = np.full((len(have), k), 1.0 / k, np.float32)
        live = np.arange(len(have))
        for left in range(k, 0, -1):
            for _ in range(ROUNDS if left > 1 else 1):
                r = like * pi[own]
                r /= np.maximum(r.sum(1, keepdims=True), 1e-30)
                pi = np.add.reduceat(r, row, axis=0) / count[:, None].astype(np.float32)
                pi = np.where(active, np.maximum(pi, 1e-6), 0).astype(np.float32)
                pi /= pi.sum(1, keepdims=True)
            fitted = base + np.add.reduceat(np.log(np.maximum((like * pi[own]).sum(1), 1e-30)).astype(np.float64), row)
            value = fitted - penalty * (active.sum(1) - 1) * np.log(count + 1)
            better = value > best
            best[better], best_pi[better], best_fit[better] = value[better], pi[better], fitted[better]
            # the weakest language leaves, and with it all that hold next to nothing, never the strongest
            shy = np.where(active, pi, np.inf)
            drop = (shy == shy.min(1, keepdims=True)) | (shy < 0.01)
            drop[live, pi.argmax(1)] = False
            active &= ~drop
            if (active.sum(1) < 1).any() or left == 1:
                break
            pi = np.where(active, pi, 0)
            pi /= np.maximum(pi.sum(1, keepdims=True), 1e-30)
        share[have] = best_pi
        fit[have] = best_fit / letters
        return share, fit, words

    def verdict(self, share: np.ndarray, fit: np.ndarray, words: np.ndarray, min_share: float) -> tuple[np.ndarray, np.ndarray]:
        if not self.langs:
            return np.full(len(words), -1), np.zeros(len(words), bool)
        top = np.where(words > 0, share.argmax(1), -1)
        return top, (words > 0) & (share.max(1) >= min_share) & (fit >= self.floors[top])


def train(docs: DataFrame, train_docs_per_lang: int = TRAIN_DOCS_PER_LANG) -> LanguageModel:
    """Trigram counts of the sample come back as one vector for each language, as do two moments of its documents' fits."""
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang")).where("lang is not null and lang <> 'und'")
    counts = {r["lang"]: r["n"] for r in named.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    langs = sorted(counts)
    if not langs:
        return LanguageModel([], np.zeros((TRIGRAMS, 0)), np.zeros(0))
    share = F.create_map(*[x for lang in langs for x in (F.lit(lang), F.lit(min(1.0, train_docs_per_lang / counts[lang])))])
    lottery = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / float(1 << 20)
    sample = keyed_docs(docs, F.col("lang").cast("string").alias("lang")).where(F.col("lang").isin(langs)).where(lottery < share[F.col("lang")])

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                code, first, doc = _word_codes(buf, offs)
                if not len(doc):
                    continue
                names = rows.column(2).to_pylist()
                of = np.repeat(np.array([langs.index(x) for x in names])[doc], np.diff(np.append(first, len(code))))
                for k in np.unique(of):
                    total[langs[k]] = total.get(langs[k], 0) + np.bincount(code[of == k], minlength=TRIGRAMS)
        for lang, v in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([lang]), pa.array([v.astype(np.int64).tobytes()], pa.binary())], ["lang", "v"])

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        v = sum(np.frombuffer(x, np.int64) for x in pdf["v"])
        return pd.DataFrame({"lang": [pdf["lang"][0]], "v": [v.tobytes()]})

    found = {r["lang"]: np.frombuffer(r["v"], np.int64) for r in sample.mapInArrow(tally, "lang string, v binary").groupBy("lang").applyInPandas(add, "lang string, v binary").collect()}
    langs = [x for x in langs if x in found]
    if not langs:
        return LanguageModel([], np.zeros((TRIGRAMS, 0)), np.zeros(0))
    logp = np.stack([np.log((found[x] + 0.1) / (found[x].sum() + 0.1 * TRIGRAMS)) for x in langs], axis=1)
    model = LanguageModel(langs, logp, np.full(len(langs), -np.inf))
    # mean and spread of a trigram's log likelihood under its own model: no second pass over texts
    p = np.exp(logp)
    mean, var = (p * logp).sum(0), (p * logp**2).sum(0)
    model.floors = mean - FLOOR_SD * np.sqrt(np.maximum(var - mean**2, 1e-9))
    return model


def detect(docs: DataFrame, model: LanguageModel, min_share: float = MIN_SHARE) -> DataFrame:
    """(doc_id, lang_found, langs, shares, accepted) of every row; langs by falling share."""
    raw = model.dump()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = LanguageModel.load(raw)
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                share, fit, words = m.infer(buf, offs)
                top, ok = m.verdict(share, fit, words, min_share)
                order = np.argsort(-share, axis=1, kind="stable") if len(m.langs) else np.empty((len(words), 0), int)
                names = [[m.langs[k] for k in o if s[k] > 0] for o, s in zip(order, share)]
                parts = [[round(float(s[k]), 4) for k in o if s[k] > 0] for o, s in zip(order, share)]
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([m.langs[t] if t >= 0 else "und" for t in top], pa.string()), pa.array(names, pa.list_(pa.string())), pa.array(parts, pa.list_(pa.float64())), pa.array(ok)], ["doc_id", "lang_found", "langs", "shares", "accepted"])

    return keyed_docs(docs).mapInArrow(run, "doc_id long, lang_found string, langs array<string>, shares array<double>, accepted boolean")


def keep_known(docs: DataFrame, model: LanguageModel, min_share: float = MIN_SHARE) -> DataFrame:
    """The rows of docs, all columns, whose language is accepted."""
    raw, schema = model.dump(), docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = LanguageModel.load(raw)
        for batch in batches:
            for rows, buf, offs in byte_slices(batch):
                yield rows.filter(pa.array(m.verdict(*m.infer(buf, offs), min_share)[1]))

    return docs.mapInArrow(run, schema)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return detect(docs, train(docs))
