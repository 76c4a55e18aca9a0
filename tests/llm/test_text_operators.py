"""Brute-force versions and edge cases of the text operators."""

from __future__ import annotations

import itertools
import math
import random
import re

import numpy as np
import pytest

from seqgrid.llm import chat, common, decontam, jaccard, language, lm_score, packing, quality, sharding

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[0-9A-Za-z\x80-\U0010ffff]+")
LONG = "word " * 40_000


def prose(rng: random.Random, n: int, vocab: int = 4000) -> str:
    out = []
    for i in range(n):
        out.append("".join(rng.choice("abcdefghijklmnop") for _ in range(2 + rng.randrange(vocab) % 6)) + (". " if i % 9 == 8 else " "))
    return "".join(out)


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], SCHEMA)


EDGE = [(1, None), (2, ""), (3, "   \n "), (4, "one"), (5, LONG), (6, "Été à l'ÉCOLE. Ça va?"), (6, "Été à l'ÉCOLE. Ça va?"), (None, "no id at all"), (7, "!!! ???"), (8, "x" * 50_000)]


def clashing(df):
    """Extra columns whose names the operators use inside."""
    from pyspark.sql import functions as F

    return df.withColumn("node", F.lit("x")).withColumn("shard", F.lit(1.5)).withColumn("quality", F.lit("q")).withColumn("words", F.lit(3)).withColumn("prefix", F.lit(None).cast("string")).withColumn("keys", F.lit(1)).withColumn("good", F.lit(2))


def bytes_of(texts):
    raw = [t.encode() for t in texts]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])])


def test_word_hashes_follow_lower_cased_words():
    texts = ["The CAT. the cat", "", "ÉTÉ été x1", "cat"]
    _, _, h, doc = common.word_table(*bytes_of(texts))
    words = [w.lower() for t in texts for w in WORD.findall(t)]
    assert len(h) == len(words) and doc.tolist() == [0, 0, 0, 0, 2, 2, 2, 3]
    for (a, x), (b, y) in itertools.combinations(zip(words, h.tolist()), 2):
        assert (a == b) == (x == y)
    assert common.word_hash("cat") == int(h[1])


# ---- packing ----


def brute_cost(tokens, penalty, capacity):
    n = len(tokens)
    best = [0] + [math.inf] * n
    for j in range(1, n + 1):
        s = 0
        for i in range(j - 1, -1, -1):
            s += tokens[i]
            if s > capacity:
                break
            best[j] = min(best[j], best[i] + capacity - s + penalty[j - 1])
    return best[n]


def test_packing_matches_quadratic_program():
    rng = np.random.default_rng(1)
    for _ in range(60):
        n, cap = rng.integers(1, 60), int(rng.integers(5, 40))
        tokens, pen = rng.integers(1, cap + 1, n), rng.choice([0, 3, 9], n)
        cuts, cost = packing.best_cuts(tokens, pen, cap)
        assert cost == brute_cost(tokens.tolist(), pen.tolist(), cap)
        at = [0, *cuts]
        assert sum(cap - tokens[a:b].sum() + pen[b - 1] for a, b in zip(at, at[1:])) == cost
        assert all(tokens[a:b].sum() <= cap for a, b in zip(at, at[1:]))


def test_packing_covers_every_text_in_order(spark):
    rng = random.Random(2)
    rows = EDGE + [(10 + i, prose(rng, rng.randrange(1, 400))) for i in range(60)]
    got = packing.pack(clashing(docs(spark, rows)), capacity=100, shard_docs=16).toPandas().sort_values(["shard", "window", "seq"])
    assert (got.groupby(["shard", "window"]).n_tokens.sum() <= 100).all()
    assert (got.groupby(["shard", "window"]).n_tokens.sum() == got.groupby(["shard", "window"]).window_tokens.first()).all()
    for i, t in dict(rows).items():
        mine = got[got.doc_id.isna() if i is None else got.doc_id == i]
        n = len((t or "").split())
        if not n:
            assert not len(mine)
            continue
        times = sum(1 for j, _ in rows if j == i)
        assert mine.n_tokens.sum() == n * times
        if times == 1:
            assert mine.start_char.iloc[0] == 0 and mine.end_char.iloc[-1] == len(t)
            assert (mine.start_char.to_numpy()[1:] == mine.end_char.to_numpy()[:-1]).all()
    assert packing.pack(docs(spark, []).limit(0)).count() == 0


def test_packing_deals_by_rank_whatever_the_ids(spark):
    """Sparse ids, an outlying one and null ones: shards of as many documents as asked, in order, each the optimum of its texts."""
    rng = random.Random(4)
    ids = [None, None, *sorted(rng.sample(range(-(10**12), 10**12), 30)), 2**62]
    rows = [(i, prose(rng, rng.randrange(20, 200))) for i in ids]
    got = packing.pack(docs(spark, rows), capacity=64, shard_docs=8).collect()
    dealt = {}
    for r in got:
        dealt.setdefault(r.shard, set()).add(r.doc_id)
    assert sorted(dealt) == [0, 1, 2, 3, 4] and [len([i for i in ids if i in dealt[k]]) for k in range(1, 5)] == [8, 8, 8, 1]
    flat = [i for k in range(5) for i in sorted(dealt[k], key=lambda x: (x is not None, x or 0))]
    assert flat == [None, *ids[2:]]
    for k in range(1, 5):
        tokens, penalty = [], []
        for i, t in rows:
            if i in dealt[k]:
                raw = np.frombuffer(t.encode(), np.uint8)
                _, _, n, hard = packing.units(raw, np.array([0, len(raw)]), 64)
                tokens += n.tolist()
                penalty += [packing.HARD if x else packing.SPLIT for x in hard[:-1]] + [0]
        mine = [r for r in got if r.shard == k]
        windows = {r.window: r.window_tokens for r in mine}
        cut_docs = sum(1 for r in mine if r.end_char < len(dict(rows)[r.doc_id]))
        assert sum(64 - w for w in windows.values()) + packing.SPLIT * cut_docs == brute_cost(tokens, penalty, 64)


# ---- language ----


def test_language_mixtures(spark):
    rng = random.Random(3)
    a = lambda n: " ".join("".join(rng.choice(["ka", "lo", "mi", "tu"]) for _ in range(3)) for _ in range(n))
    b = lambda n: " ".join("".join(rng.choice(["ßer", "ung", "sch", "ein"]) for _ in range(2)) for _ in range(n))
    train = [(i, a(80), "aa", "s", 0) for i in range(30)] + [(100 + i, b(80), "bb", "s", 0) for i in range(30)]
    model = language.train(spark.createDataFrame(train, SCHEMA))
    rows = [(1, a(60)), (2, b(60)), (3, a(60) + " " + b(60)), (4, None), (5, ""), (6, "123 456 !!"), (3, a(60) + " " + b(60)), (7, a(30_000))]
    got = {(r.doc_id, tuple(r.langs)): r for r in language.detect(clashing(docs(spark, rows)), model).collect()}
    of = {k[0]: v for k, v in got.items()}
    assert of[1].langs == ["aa"] and of[2].langs == ["bb"] and of[7].langs == ["aa"]
    assert sorted(of[3].langs) == ["aa", "bb"] and abs(max(of[3].shares) - 0.5) < 0.1
    assert all(of[k].lang_found == "und" and not of[k].accepted and of[k].langs == [] for k in (4, 5, 6))
    none = language.train(spark.createDataFrame([(1, "x", None, "s", 1)], SCHEMA))
    assert [r.lang_found for r in language.detect(docs(spark, [(1, "abc")]), none).collect()] == ["und"]
    assert language.detect(docs(spark, []), model).count() == 0


def test_language_proportions_are_a_maximum():
    """On fixed word likelihoods the proportions reach at least the likelihood of a fine grid of mixtures."""
    rng = np.random.default_rng(4)
    model = language.LanguageModel(["a", "b"], rng.normal(-9, 2, (language.TRIGRAMS, 2)), np.full(2, -np.inf))
    text = prose(random.Random(5), 300)
    buf, offs = bytes_of([text])
    share, _, _ = model.infer(buf, offs, penalty=0)
    code, first, _ = language._word_codes(buf, offs)
    ll = np.add.reduceat(model.logp[code].astype(np.float64), first, axis=0)
    value = lambda p: np.logaddexp(ll[:, 0] + np.log(p), ll[:, 1] + np.log(1 - p)).sum()
    best = max(value(p) for p in np.linspace(0.005, 0.995, 199))
    assert value(np.clip(share[0, 0], 1e-9, 1 - 1e-9)) > best - 1.0


# ---- decontamination ----


def test_lcs_matches_dynamic_program():
    rng = np.random.default_rng(6)
    for _ in range(100):
        a, b = rng.integers(0, 6, rng.integers(1, 30)), rng.integers(0, 6, rng.integers(0, 40))
        t = np.zeros((len(a) + 1, len(b) + 1), int)
        for i in range(len(a)):
            for j in range(len(b)):
                t[i + 1, j + 1] = t[i, j] + 1 if a[i] == b[j] else max(t[i, j + 1], t[i + 1, j])
        assert decontam.lcs(a, b) == t[-1, -1]


def test_randomised_svd_finds_the_spectrum(spark):
    """Against a dense SVD: TF-IDF rows of 300 passages that mix 12 topics, at a rank far below the passages."""
    rng = np.random.default_rng(7)
    topics = rng.dirichlet(np.full(500, 0.02), 12)
    vocab = np.sort(common.mix(np.arange(1, 501, dtype=np.uint64)))
    words = [vocab[rng.choice(500, 64, p=topics[i % 12])] for i in range(300)]
    idf = rng.uniform(0.1, 3, 500)
    a = np.zeros((300, 500))
    for i, w in enumerate(words):
        np.add.at(a[i], np.searchsorted(vocab, w), 1)
    a *= idf
    df = spark.createDataFrame([(bytes(w.tobytes()),) for w in words], "words binary").repartition(3)
    v, s = decontam.randomised_svd(df, vocab, idf, 12)
    exact = np.linalg.svd(a, compute_uv=False)
    assert np.allclose(v.T @ v, np.eye(12), atol=1e-8) and np.allclose(s, exact[:12], rtol=0.01)
    assert np.linalg.norm(a - a @ v @ v.T) <= 1.01 * np.sqrt((exact[12:] ** 2).sum())


def test_decontamination_recall_against_all_pairs(spark):
    """Paraphrases (words replaced, dropped and put in) against the checks of every window and passage without retrieval."""
    rng = random.Random(31)
    vocab = [prose(rng, 1).strip(" .") + str(i % 7) for i in range(900)]
    say = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    items = [(i, say(rng.choice((12, 35, 64, 130)))) for i in range(160)]
    rows = []
    for i in range(220):
        words = items[i % 160][1].split()
        share = rng.choice((0.1, 0.25, 0.4))
        kept = [w if rng.random() > share else rng.choice((rng.choice(vocab), "")) for w in words[:-6]] + words[-6:]
        rows.append((i, say(rng.randrange(150)) + " " + " ".join(kept) + " " + say(rng.randrange(150))))
    rows += [(1000 + i, say(300)) for i in range(60)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    found = {(r.doc_id, r.item_id) for r in decontam.find(docs(spark, rows), bench).collect()}
    pieces = decontam.passages(bench).collect()
    want = set()
    for i, t in rows:
        raw = np.frombuffer(t.encode(), np.uint8)
        h = common.word_table(raw, np.array([0, len(raw)]))[2]
        for lo in range(0, len(h), decontam.PASSAGE):
            for r in pieces:
                item, answer = (np.frombuffer(r[c], np.uint64) for c in ("words", "answer"))
                if decontam.judge(item, answer, h[lo : lo + 2 * decontam.PASSAGE])[2]:
                    want.add((i, r["item_id"]))
    assert found <= want and len(found) >= 0.95 * len(want) and len(want) > 150
    # a benchmark of several passes over the documents
    assert {(r.doc_id, r.item_id) for r in decontam.find(docs(spark, rows), bench, most=100).collect()} == found


def test_decontamination(spark):
    rng = random.Random(8)
    items = [(i, prose(rng, 30 + i)) for i in range(12)] + [(50, prose(rng, 150)), (60, None), (61, ""), (62, "two words")]
    hide = lambda t: prose(rng, 200) + " " + t + " " + prose(rng, 150)
    words = items[3][1].split()
    for k in (5, 12, 19, 26):
        words[k] = "replaced"
    rows = EDGE + [(100 + i, prose(rng, 300)) for i in range(40)] + [(200 + i, hide(items[i][1])) for i in range(6)] + [(300, hide(" ".join(words))), (301, hide(items[12][1])), (200, hide(items[0][1])), (302, hide(items[5][1].upper().replace(".", "!")))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontam.find(clashing(docs(spark, rows)), bench).collect()}
    assert got == {(200 + i, i) for i in range(6)} | {(300, 3), (301, 50), (302, 5)}
    left = decontam.drop_leaks(docs(spark, rows), bench)
    assert left.columns == docs(spark, []).columns
    assert sorted(x.doc_id for x in left.where("doc_id >= 100").collect()) == [100 + i for i in range(40)]
    assert left.where("doc_id < 100 or doc_id is null").count() == len(EDGE)
    assert decontam.find(docs(spark, rows), bench.limit(0)).count() == 0 and decontam.find(docs(spark, []), bench).count() == 0


def test_widespread_leaks_are_found(spark):
    """A passage in a quarter of the documents, and one of which only a part is so widespread."""
    rng = random.Random(23)
    items = [(i, prose(rng, 40)) for i in range(3)]
    part = " ".join(items[1][1].split()[:32])
    rows = [(i, prose(rng, 200) + " " + {0: items[0][1], 1: part}.get(i % 4, "") + " " + prose(rng, 90)) for i in range(24)]
    got = {(r.doc_id, r.item_id) for r in decontam.find(docs(spark, rows), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == {(i, i % 4) for i in range(24) if i % 4 < 2}


# ---- cross-parsing ----


def brute_phrases(z, r):
    i = c = 0
    while i < len(z):
        k = 1
        while i + k <= len(z) and z[i : i + k] in r:
            k += 1
        i, c = i + max(1, k - 1), c + 1
    return c


def brute_own(z):
    seen, c, cur = set(), 0, b""
    for x in z:
        cur += bytes([x])
        if cur not in seen:
            seen.add(cur)
            c, cur = c + 1, b""
    return c + bool(cur)


def test_cross_parsing_matches_substring_search():
    rng = np.random.default_rng(9)
    for _ in range(40):
        r, z = (rng.integers(0, 5, n).tolist() for n in (rng.integers(1, 300), rng.integers(1, 200)))
        z = [9 if x == 4 else x for x in z]
        starts = lm_score.SuffixAutomaton(r).match_starts(z)
        assert starts == sorted(starts) and lm_score.factor(starts) == brute_phrases(bytes(z), bytes(r))
        assert lm_score.own_phrases(z, 10) == brute_own(bytes(z))


def corpus_for_scores():
    rng = random.Random(10)
    shared = prose(rng, 300)
    rows = [(20 + i, prose(rng, 120)) for i in range(40)]
    rows += [(100, rows[5][1]), (101, prose(rng, 40) + " " + shared + " " + prose(rng, 40)), (102, prose(rng, 60) + " " + shared), (103, "zzzz qqqq " * 60), (104, "zzzz qqqq " * 60 + "end"), (105, "日本語の文章 abc 日本"), (105, "日本語の文章 abc 日本")]
    return rows


def brute_scores(rows, shard_bytes=None):
    """phrases by (id, text): substring search in all other documents of the corpus."""
    out = {}
    texts = {}
    for i, t in set(rows):
        raw = np.frombuffer(t.encode(), np.uint8)
        texts[i, t] = lm_score.words(raw, np.array([0, len(raw)]))[0].tolist()
    for k, z in texts.items():
        grams = [tuple(v) for j, v in texts.items() if j != k]
        text = "|".join("_" + "_".join(map(str, g)) + "_" for g in grams)
        i = count = 0
        while i < len(z):
            m = 0
            while i + m < len(z) and "_".join(["", *map(str, z[i : i + m + 1]), ""]) in text:
                m += 1
            i, count = i + max(m, 1), count + 1
        out[k] = count
    return out


def test_lm_scores(spark):
    rows = EDGE + corpus_for_scores()
    got = lm_score.score(clashing(docs(spark, rows))).toPandas()
    assert len(got) == len(rows)
    by = got.set_index("doc_id")
    assert by.loc[[1, 2, 3]].cross_entropy.isna().all()
    assert by.loc[list(range(20, 60))].cross_entropy.notna().all()
    assert by.loc[105].phrases.nunique() == 1 and by.loc[25].phrases == by.loc[100].phrases == 1
    n = by.loc[26].n_words
    assert by.loc[26].cross_entropy == pytest.approx(by.loc[26].phrases * math.log2(n) / n, abs=1e-5)
    assert by.loc[26].divergence == pytest.approx((by.loc[26].phrases * math.log2(n) - by.loc[26].own_phrases * math.log2(by.loc[26].own_phrases)) / n, abs=1e-5)
    assert lm_score.score(docs(spark, [])).count() == 0
    assert lm_score.score(docs(spark, [(1, "one document alone")])).first()["phrases"] is None


def test_lm_scores_against_all_other_documents(spark):
    """Never fewer phrases than a search in the whole corpus finds, and few more; long repeats in another shard are found."""
    rows = corpus_for_scores()
    brute = {k[0]: v for k, v in brute_scores(rows).items()}
    for shard_bytes in (1 << 23, 4000):
        got = {r["doc_id"]: r["phrases"] for r in lm_score.score(docs(spark, rows), shard_bytes).collect() if r["phrases"] is not None}
        assert all(v >= brute[k] for k, v in got.items())
        assert got[25] == got[100] == 1
        assert got[101] <= 80 + 34 + 5 and got[102] <= 60 + 34 + 5  # the shared passage but for a chunk at each end
    assert sum(got.values()) <= 1.6 * sum(brute[k] for k in got)


def test_lm_scores_of_the_whole_corpus_miss_no_match(spark):
    """The very numbers of a search in all other documents, in one part and in many; a short passage that two documents far apart share counts."""
    rng = random.Random(41)
    short = prose(rng, 9)  # less than a chunk
    rows = corpus_for_scores() + [(200 + i, prose(rng, 50) + " " + short + " " + prose(rng, 50)) for i in range(4)]
    brute = {k[0]: v for k, v in brute_scores(rows).items()}
    for part_bytes in (1 << 22, 4000):
        got = lm_score.score_whole(clashing(docs(spark, EDGE[:3] + rows)), part_bytes).collect()
        assert len(got) == len(rows) + 3
        assert {r.doc_id: r.phrases for r in got if r.doc_id > 3} == brute
        assert all(r.phrases is None and r.n_words == 0 for r in got if r.doc_id <= 3)
        one = next(r for r in got if r.doc_id == 26)
        assert one.cross_entropy == pytest.approx(one.phrases * math.log2(one.n_words) / one.n_words, abs=1e-5)
    assert lm_score.score_whole(docs(spark, [])).count() == 0 and lm_score.score_whole(docs(spark, [(1, "one document alone")])).first()["phrases"] is None


def near_copies(rng: random.Random, texts: int, words: int, edits: int):
    """Texts that differ from one another in many single words: a match between two has many ends of other matches inside."""
    base = prose(rng, words).split()
    out = []
    for i in range(texts):
        copy = list(base)
        for k in rng.sample(range(words), edits):
            copy[k] = rng.choice(base)
        out.append((300 + i, " ".join(copy)))
    return out


def test_lm_scores_of_near_copies_miss_no_match(spark):
    """Matches with more than RANKS ends of others inside, in one pack and in many, in one bin and in pairs of its blocks."""
    rng = random.Random(43)
    rows = corpus_for_scores() + near_copies(rng, 30, 250, 6) + [(400, near_copies(rng, 1, 200, 0)[0][1])]
    rows += [(401, rows[50][1].upper()), (402, rows[60][1]), (402, rows[60][1])]
    brute = {k[0]: v for k, v in brute_scores(rows).items()}
    for part_bytes in (1 << 22, 8000, 1000):
        got = lm_score.score_whole(docs(spark, rows), part_bytes).collect()
        assert len(got) == len(rows) and {r.doc_id: r.phrases for r in got} == brute


def test_other_reach_matches_substring_search():
    rng = np.random.default_rng(5)
    for _ in range(60):
        base = rng.integers(1, rng.integers(3, 9), 60)
        texts = [bytes(base[(s := rng.integers(0, 30)) : s + n].tolist()) if rng.random() < 0.6 else bytes(rng.integers(1, 6, n).tolist()) for n in rng.integers(1, 30, rng.integers(1, 7))]
        got = lm_score.other_reach(np.frombuffer(b"".join(texts), np.uint8).astype(np.uint64), np.repeat(np.arange(len(texts)), [len(t) for t in texts])).tolist()
        for k, t in enumerate(texts):
            others = [x for j, x in enumerate(texts) if j != k]
            assert [got.pop(0) for _ in t] == [max(n for n in range(len(t) - i + 1) if not n or any(t[i : i + n] in x for x in others)) for i in range(len(t))]


def shuffled(spark, df) -> int:
    """Bytes that the stages of an action write for a shuffle."""
    sc = spark.sparkContext
    total = lambda: sum(sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None).apply(k).shuffleWriteBytes() for k in range(sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None).size()))
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    before = total()
    df().collect()
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    return total() - before


def test_lm_scores_shuffle_in_proportion_to_the_corpus(spark):
    """Texts are not copied to pairs of parts: four times the texts in parts of one size, about four times the bytes."""
    rng = random.Random(44)
    rows = [(i, prose(rng, 400)) for i in range(400)]
    few, many = (shuffled(spark, lambda n=n: lm_score.score_whole(docs(spark, rows[:n]), 40_000)) for n in (100, 400))
    assert 0 < many < 6 * few


def test_chunks_stand_where_the_words_say(spark):
    rng = random.Random(3)
    text = prose(rng, 400)
    two = [prose(rng, 30) + " " + text, text]
    raw = [np.frombuffer(t.encode(), np.uint8) for t in two]
    every = []
    for r in raw:
        h, doc = lm_score.words(r, np.array([0, len(r)]))
        every.append(set(lm_score.chunk_hashes(h, lm_score.chunk_starts(h, doc)).tolist()))
    assert len(every[0] & every[1]) >= len(every[1]) - 1
    both = np.concatenate(raw)
    h, doc = lm_score.words(both, np.array([0, len(raw[0]), len(both)]))
    start = lm_score.chunk_starts(h, doc)
    value = lm_score.chunk_hashes(h, start)
    assert set(value[doc[start] == 0].tolist()) == every[0] and set(value[doc[start] == 1].tolist()) == every[1]


# ---- chat ----


def test_chat_expansion(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "yo"), (1, 2, "user", None), (1, 3, " Assistant ", "ok"), (2, 0, "assistant", "first"), (None, 0, "assistant", "x"), (3, 0, "user", "alone"), (4, 1, None, "?"), (4, None, "assistant", "last"), (4, 2, "assistant", "a"), (4, 2, "assistant", "a")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    from pyspark.sql import functions as F

    got = chat.expand(df.withColumn("m", F.lit(1)).withColumn("shown", F.lit("x"))).collect()
    part = lambda r: (r.example[: r.train_start], r.example[r.train_start : r.train_end])
    of = {(r.conv_id, r.turn, r.n_context): part(r) for r in got}
    assert set(of) == {(1, 1, 1), (1, 3, 3), (2, 0, 0), (4, None, 3), (4, 2, 1), (4, 2, 2)}
    assert of[1, 3, 3] == ("<|user|>\nhi<|end|>\n<|assistant|>\nyo<|end|>\n<|user|>\n<|end|>\n<|assistant|>\n", "ok<|end|>\n")
    assert of[2, 0, 0] == ("<|assistant|>\n", "first<|end|>\n")
    assert all(r.train_end == len(r.example) for r in got) and chat.expand(df.limit(0)).count() == 0


# ---- Jaccard join ----


def grams(text, width=3):
    w = [x.lower() for x in WORD.findall(text or "")]
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def brute_pairs(rows, threshold):
    sets = {i: grams(t) for i, t in rows if i is not None}
    out = {}
    for a, b in itertools.combinations(sorted(sets), 2):
        if sets[a] and sets[b] and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= threshold:
            out[a, b] = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
    return out


def near_rows(seed=12):
    rng = random.Random(seed)
    rows = [(100 + i, prose(rng, rng.randrange(20, 200))) for i in range(60)]
    for k in range(40):
        i, t = rng.choice(rows[:60])
        w = t.split(" ")
        for _ in range(rng.randrange(0, max(1, len(w) // 8))):
            w[rng.randrange(len(w))] = "changed%d" % rng.randrange(99)
        rows.append((1000 + k, " ".join(w)))
    rows += [(2000 + k, rows[5][1].upper()) for k in range(12)]
    shared = prose(rng, 60)
    return rows + [(3000 + k, prose(rng, 200) + shared + prose(rng, 200)) for k in range(20)]


def test_jaccard_join_matches_all_pairs(spark, monkeypatch):
    rows = near_rows()
    want = brute_pairs(rows, 0.5)
    for block in (jaccard.BLOCK_TOKENS, 500):
        monkeypatch.setattr(jaccard, "BLOCK_TOKENS", block)
        pairs, _ = jaccard.join(clashing(docs(spark, rows)))
        got = {(r.doc_id_a, r.doc_id_b): r.jaccard for r in jaccard.expand(pairs).collect()}
        assert set(got) <= set(want) and len(got) >= 0.97 * len(want)
        assert all(abs(want[k] - v) < 1e-5 for k, v in got.items())


def test_jaccard_lists_the_pairs_of_all_rows(spark, monkeypatch):
    """Copies and near copies of them: every_pair gives every pair, also where the copies fill several blocks."""
    rng = random.Random(21)
    text = prose(rng, 100)
    near = text.replace(" ", " changed ", 1)
    rows = [(k, text) for k in range(9)] + [(20 + k, near) for k in range(3)] + [(40, prose(rng, 80)), (40, text), (None, text)]
    monkeypatch.setattr(jaccard, "BLOCK_IDS", 4)
    got = [(r.doc_id_a, r.doc_id_b) for r in jaccard.every_pair(docs(spark, rows)).collect()]
    assert len(got) == len(set(got)) and set(got) == set(itertools.combinations([*range(9), 20, 21, 22, 40], 2))


def test_jaccard_query_has_a_row_for_each_document(spark, tmp_path, monkeypatch):
    """Class and number of links of every document against all pairs, also where groups are cut in many blocks."""
    rng = random.Random(24)
    text = prose(rng, 100).split(" ")
    chain = [(4000 + k, " ".join(text[k : k + 60])) for k in range(0, 40, 3)]  # a class whose ends are not alike
    rows = near_rows() + chain + [(2100 + k, chain[3][1]) for k in range(5)]
    want = brute_pairs(rows, 0.5)
    root, links = {i: i for i, _ in rows}, dict.fromkeys((i for i, _ in rows), 0)

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in want:
        links[a], links[b] = links[a] + 1, links[b] + 1
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    assert find(chain[0][0]) == find(chain[-1][0]) and (chain[0][0], chain[-1][0]) not in want
    odd = [rows[0], (None, rows[0][1]), (1, None), (2, ""), (9000, "alone among the others")]
    clashing(docs(spark, rows + odd)).write.parquet(f"{tmp_path}/documents.parquet")
    for block in (jaccard.BLOCK_TOKENS, 500):
        monkeypatch.setattr(jaccard, "BLOCK_TOKENS", block)
        got = jaccard.op6_ngram_jaccard_join(spark, str(tmp_path)).collect()
        assert sorted(r.doc_id for r in got) == sorted([*root, 1, 2, 9000])
        of = {r.doc_id: r for r in got}
        assert all((of[i].class_id, of[i].links) == (i, 0) for i in (1, 2, 9000))
        assert sum(of[i].class_id != find(i) for i in root) <= 2
        assert all(of[i].links <= links[i] for i in root) and sum(of[i].links for i in root) >= 0.97 * sum(links.values())
    assert jaccard.classes(docs(spark, [])).count() == 0


def test_jaccard_memory_follows_the_rows_not_the_pairs():
    """A block of texts that are all alike: millions of links, of which a forest and numbers stay."""
    import tracemalloc

    import pyarrow as pa

    n = 3000
    sets = [np.append(np.arange(20, dtype=np.uint64), np.uint64(100 + i)) for i in range(n)]
    t = pa.table({"member": [True] * n, "rep": range(n), "node": range(n), "texts": [1] * n, "n": pa.array([21] * n, pa.int32()), "tokens": [x.tobytes() for x in sets]})
    for job in (jaccard._matrix_join(0.5, True), jaccard._matrix_links(0.5)):
        tracemalloc.start()
        out = job(t).to_pandas()
        most = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert most < 24 << 20
        assert len(out) == n - 1 if "jaccard" in out else (out.links > 0).sum() == n and (out.links[out.links > 0] == n - 1).all() and (out.links == 0).sum() == n - 1


def test_jaccard_tasks_hold_two_blocks(spark, monkeypatch):
    """Whatever a group's members and probes are, a task holds two blocks or so, and each pair that has to meet does so once."""
    monkeypatch.setattr(jaccard, "BLOCK_TOKENS", 400)
    active = spark.createDataFrame([(k, k, 10, 7) for k in range(300)] + [(1000, 1000, 10, 8)], "node long, rep long, n int, g long")
    probes = spark.createDataFrame([(5000 + k, 7, 10) for k in range(200)] + [(5000, 8, 10)], "node long, g long, n int")
    tasks = {}
    for r in jaccard._places(active, probes).collect():
        tasks.setdefault((r.g, r.lo, r.hi), ([], []))[not r.member].append(r.node)
    assert max(10 * len(x) for both in tasks.values() for x in both) <= 2 * 2 * 400
    met = []
    for (g, lo, hi), (left, right) in tasks.items():
        met += [(g, *sorted(p)) for p in itertools.product(left, right)]
        met += [(g, *p) for p in itertools.combinations(sorted(left), 2)] if lo == hi else []
    assert len(met) == len(set(met))
    assert set(met) == {(7, a, b) for a, b in itertools.combinations(range(300), 2)} | {(7, a, 5000 + b) for a in range(300) for b in range(200)} | {(8, 1000, 5000)}


def test_jaccard_groups_keep_one(spark):
    rows = near_rows(13) + EDGE
    want = brute_pairs(rows, 0.5)
    root = {i: i for i, _ in rows if i is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in want:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    kept = jaccard.keep_one(docs(spark, rows))
    ids = [r.doc_id for r in kept.collect()]
    lone = {i for i in root if find(i) == i}
    assert set(ids) - {None} >= lone and len(set(ids) - {None} - lone) <= 2
    assert ids.count(6) == 1 and ids.count(None) == 1 and {1, 2, 3, 7} <= set(ids)
    assert jaccard.join(docs(spark, []))[0].count() == 0 and jaccard.keep_one(docs(spark, [])).count() == 0


def test_groups_open_by_bound():
    """A foreign query below the bound is not opened; one above it is matched exactly."""
    import pyarrow as pa

    member = np.arange(100, dtype=np.uint64)
    near, far = np.arange(10, 110, dtype=np.uint64), np.arange(90, 190, dtype=np.uint64)
    t = pa.table({"member": [True, False, False], "rep": [1, 2, 3], "n": pa.array([100, 100, 100], pa.int32()), "tokens": [x.tobytes() for x in (member, near, far)]})
    out = jaccard._matrix_join(0.5, False)(t).to_pylist()
    assert out == [{"doc_id_a": 1, "doc_id_b": 2, "jaccard": round(90 / 110, 6)}]


# ---- classifier ----


def test_classifier_learns_and_covers_the_whole_text(spark):
    rng = random.Random(14)
    good = [prose(rng, 150) for _ in range(120)]
    bad = [" ".join(w.upper() + "!!" for w in prose(rng, 150).split()) for _ in range(120)]
    net = quality.fit([t.encode() for t in good[:80] + bad[:80]], np.array([1] * 80 + [0] * 80))
    p = lambda texts: net.predict(*bytes_of(texts))
    assert (p(good[80:]) > 0.5).mean() > 0.95 and (p(bad[80:]) < 0.5).mean() > 0.95
    # chunks at the far end count as the first ones do
    a, b = net.features(*bytes_of([good[0] * 8 + bad[0] * 8])), net.features(*bytes_of([good[0] * 16]))
    assert np.abs(a - b).max() > 0.1
    # in any company the same scores
    assert np.allclose(p(good[:9]), np.concatenate([p([t]) for t in good[:9]]), atol=1e-6)
    back = quality.ByteCNN.load(net.dump())
    assert np.allclose(back.predict(*bytes_of(good[:3])), p(good[:3]))
    got = {r.doc_id: r for r in quality.score(clashing(docs(spark, EDGE)), net).collect()}
    assert got[1].p_quality == got[2].p_quality == 0 and not got[1].accepted and len(got) == len({i for i, _ in EDGE})


def test_classifier_rejects_toxic_documents_of_good_quality(spark):
    rng = random.Random(22)
    rows, labels = [], []
    for i in range(400):
        words, toxic = prose(rng, 60).split(" "), i % 4 == 0
        for _ in range(3 * toxic):
            words.insert(rng.randrange(len(words)), rng.choice(["xquorgh", "zzvark"]))
        rows.append((i, " ".join(words)))
        labels.append((i, 1, int(toxic)))
    labels = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {r.doc_id: r.accepted for r in quality.score(docs(spark, rows[300:]), quality.train(docs(spark, rows[:300]), labels)).collect()}
    assert sum(got[i] for i in got if i % 4 == 0) <= 2 and sum(not got[i] for i in got if i % 4) <= 4


def test_classifier_direct_convolution():
    rng = np.random.default_rng(15)
    w = rng.normal(size=(quality.TAPS, 256, 3)).astype(np.float32)
    net = quality.ByteCNN(w, rng.normal(size=3).astype(np.float32), np.ones(6, np.float32), 0.0)
    text = bytes(rng.integers(1, 255, 2001, dtype=np.uint8))
    got = net.features(np.frombuffer(text, np.uint8), np.array([0, len(text)]))[0]
    raw = text + bytes(quality.TAPS + 2)
    n = (len(text) + 1) // 2
    z = np.array([sum(w[k, raw[2 * j + k]] for k in range(quality.TAPS)) for j in range(n + 1)])  # the last one sees padding only
    chunks = max(1, -(-n // quality.STEP) - 1)
    tops = np.array([z[h * quality.STEP : h * quality.STEP + quality.CHUNK if h + 1 < chunks else None].max(0) for h in range(chunks)])
    r = np.maximum(tops + net.b, 0)
    assert np.allclose(got[:3], r.mean(0), atol=1e-4) and np.allclose(got[3:], r.max(0), atol=1e-4)


def test_classifier_without_labels(spark):
    rows = docs(spark, [(1, "a"), (2, None)])
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r.p_quality for r in quality.score(rows, quality.train(rows, none)).orderBy("doc_id").collect()] == [0.5, 0.0]
    one = spark.createDataFrame([(1, 1, 0), (1, 1, 0)], "doc_id long, quality int, toxic int")
    assert quality.keep_good(rows, quality.train(rows, one)).count() == 1


# ---- sharding ----


def test_sharding_is_the_split_of_oversized_buckets(spark):
    rng = random.Random(16)
    rows = [(i, "x" * rng.randrange(0, 900)) for i in range(200)] + [(500, "y" * 9000), (7, "x" * 100), (None, "n"), (501, None)]
    limit = 3000
    got = sharding.assign(clashing(docs(spark, rows)), limit).collect()
    assert len(got) == len(rows)
    import hashlib

    bits = lambda i: bin(int(hashlib.md5(("" if i is None else str(i)).encode()).hexdigest()[:15], 16))[2:].zfill(60)
    load = lambda prefix: sum(len(t or "") for i, t in rows if bits(i).startswith(prefix))
    for r in got:
        assert bits(r.doc_id).startswith(r.shard) and r.depth == len(r.shard) and r.shard_bytes == load(r.shard)
        assert r.fits == (r.shard_bytes <= limit) and (r.fits or r.depth == 60)
        assert not r.depth or load(r.shard[:-1]) > limit
    assert sharding.assign(docs(spark, []), limit).count() == 0
