"""The pipeline against brute force, stage by stage, on the smallest tables."""

from __future__ import annotations

import pyarrow.parquet as pq

import corpus_pipeline as P
from seqgrid.llm import packing
from tests.llm.test_text_operators import WORD, brute_pairs, docs


def test_stages(spark, sf):
    assert [n for n, _ in P.STAGES] == ["quality_classifier", "language_id", "ngram_jaccard_join", "benchmark_decontamination", "packing"]
    now = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = now.columns, []
    for name, stage in P.STAGES:
        before = {r.doc_id: r for r in now.collect()}
        now = stage(spark, now, sf)
        if name != "packing":
            assert now.columns == columns
            after = {r.doc_id: r for r in now.collect()}
            assert len(after) == now.count() and all(after[i] == before[i] for i in after)
        seen.append((name, before, after))
    labels = {i: (q, t) for i, q, t in zip(*(pq.read_table(f"{sf}/labels.parquet")[c].to_pylist() for c in ("doc_id", "quality", "toxic")))}
    _, before, after = seen[0]
    good = [i for i in before if labels.get(i) == (1, 0)]  # toxic documents are rejects, whatever their quality
    toxic = [i for i in before if labels.get(i, (0, 0))[1] == 1]
    assert sum(i in after for i in good) >= 0.99 * len(good) and sum(i in after for i in toxic) <= 0.5 * len(toxic)
    _, before, after = seen[1]
    assert len(after) >= 0.98 * len(before)
    _, before, after = seen[2]
    root = {i: i for i in before}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in brute_pairs([(i, r.text) for i, r in before.items()], 0.5):
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    lone = {i for i in root if find(i) == i}
    assert lone <= set(after) and len(set(after) - lone) <= 2
    _, before, after = seen[3]
    items = [[w.lower() for w in WORD.findall(t)] for t in pq.read_table(f"{sf}/benchmark.parquet")["text"].to_pylist()]
    inside = lambda t: any(f" {' '.join(i)} " in f" {' '.join(w.lower() for w in WORD.findall(t))} " for i in items)
    assert set(before) - set(after) == {i for i, r in before.items() if inside(r.text)}
    rows = now.toPandas()
    assert rows.groupby("doc_id").n_tokens.sum().to_dict() == {i: len(r.text.split()) for i, r in after.items()}
    assert (rows.groupby(["shard", "window"]).n_tokens.sum() <= packing.CAPACITY).all()


def test_run_writes_and_returns_the_last_stage(spark, sf):
    assert set(P.run(spark, sf).columns) == {"shard", "window", "seq", "doc_id", "start_char", "end_char", "n_tokens", "window_tokens"}


def test_stages_take_empty_and_odd_tables(spark, sf):
    odd = docs(spark, [(1, None), (2, ""), (3, "one"), (3, "one"), (None, "null id"), (4, "word " * 20_000)])
    for table in (odd, odd.limit(0)):
        now = table
        for _, stage in P.STAGES:
            now = stage(spark, now, sf)
        now.count()
