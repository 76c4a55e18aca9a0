"""Score, search, views and sources against direct computation, exact enumeration and planted truth."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqgrid.functions import encode, mathx
from seqgrid.operators import accuracy, assign, grid, hierarchy, insight, merge, refine, score, typical
from seqgrid.plans import baseline, kernel
from seqgrid.plans import fit as fits
from seqgrid.sources import persist, points, synth, workloads


def data(rng, ns=6, nt=9, ne=4, n=80):
    s, t, e = rng.integers(0, ns, n), np.sort(rng.integers(0, nt, n)), rng.integers(0, ne, n)
    code = lambda x: np.unique(x, return_inverse=True)[1]
    s, t, e = code(s), code(t), code(e)
    return kernel.Data(s, t, e, rng.integers(1, 4, n), s.max() + 1, t.max() + 1, e.max() + 1)


def parts(rng, d, k=3):
    cuts = np.zeros(d.nt, int)
    cuts[rng.choice(np.arange(1, d.nt), k - 1, replace=False)] = 1
    return kernel.Parts(rng.integers(0, k, d.ns), np.cumsum(cuts), rng.integers(0, k, d.ne)).tidy(d)


def literal_cost(d, p, prior="at_most"):
    """The eight terms written out."""
    x = kernel.tensor(d, p)
    ks, kt, ke = x.shape
    n, a, N, k = d.ns, d.ne, d.N, x.size
    lf, c = mathx.lf, mathx.ln_choose
    ms, me = np.bincount(p.s), np.bincount(p.e)
    out = math.log(n) + math.log(a) + math.log(N) + mathx.ln_b(n, ks, prior) + mathx.ln_b(a, ke, prior) + c(N + k - 1, k - 1)
    for i in range(ks):
        out += c(x[i].sum() + ms[i] - 1, ms[i] - 1) + lf(x[i].sum())
    for i in range(ke):
        out += c(x[:, :, i].sum() + me[i] - 1, me[i] - 1) + lf(x[:, :, i].sum())
    out += lf(N) - sum(lf(v) for v in x.ravel()) + sum(lf(x[:, j].sum()) for j in range(kt))
    for own, k_ in ((d.s, n), (d.e, a)):
        out -= sum(lf(v) for v in np.bincount(own, d.n, k_))
    return out


def test_partition_numbers():
    bell = {1: 1, 2: 2, 3: 5, 4: 15, 5: 52, 10: 115975}
    for n, b in bell.items():
        assert mathx.ln_b(n, n) == pytest.approx(math.log(b)) and mathx.ln_b(n, 1) == pytest.approx(0)
    assert math.exp(mathx.ln_b(4, 2)) == pytest.approx(8) and math.exp(mathx.ln_b(4, 2, "exact")) == pytest.approx(7)
    assert math.exp(mathx.ln_b(5, 3)) == pytest.approx(41) and math.exp(mathx.ln_b(5, 3, "exact")) == pytest.approx(25)
    for n, k in ((3000, 2), (3000, 50), (3000, 900), (3000, 2990)):
        assert mathx._ln_stirling_far(n, k) == pytest.approx(mathx._stirling_row(n, k)[-1], rel=2e-4)


def test_log_columns(spark):
    xs = [*range(0, 40), 170, 10**4, 10**7, 10**12]
    df = spark.createDataFrame([(x,) for x in xs], "x long")
    for r in df.select("x", mathx.ln_fact(F.col("x")).alias("a"), mathx.ln_gamma_step(F.col("x") + 1, F.lit(5)).alias("b")).collect():
        assert r.a == pytest.approx(math.lgamma(r.x + 1), rel=1e-14, abs=1e-14)
        exact = sum(math.log(r.x + 1 + i) for i in range(5))
        assert r.b == pytest.approx(exact, rel=1e-9)


def test_kernel_cost_is_the_criterion():
    rng = np.random.default_rng(1)
    for _ in range(20):
        d = data(rng)
        p = parts(rng, d)
        assert kernel.total(d, p) == pytest.approx(literal_cost(d, p))
        assert kernel.total(d, kernel.null_parts(d)) == pytest.approx(literal_cost(d, kernel.null_parts(d)))


def test_merge_changes_equal_rescoring():
    rng = np.random.default_rng(2)
    for _ in range(8):
        d = data(rng)
        p = kernel.Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne))
        m, now = kernel.Merger(d, p), kernel.total(d, p)
        while b := m.best():
            m.merge(*b[1:])
            then = kernel.total(d, m.parts())
            assert then - now == pytest.approx(b[0], abs=1e-8)
            now = then
        assert now == pytest.approx(kernel.total(d, kernel.null_parts(d)))


def test_incremental_path_is_the_literal_one():
    rng = np.random.default_rng(3)
    for _ in range(5):
        d = data(rng, n=40)
        p = kernel.Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne))
        a, b = kernel.greedy(d, p)[1], kernel.greedy_reference(d, p)[1]
        assert [x[:3] for x in a] == [x[:3] for x in b]


def test_alike_sequences_are_merged_as_kinds():
    """Three thousand sequences of four kinds: pairs of kinds only, and the literal path where there are few of each."""
    rng = np.random.default_rng(11)
    kinds = [[(0, 0), (1, 1)], [(0, 0), (1, 1), (2, 1)], [(0, 1)], [(1, 0), (2, 0)]]

    def many(k):
        rows = [(s, t, e) for s in range(k) for t, e in kinds[int(rng.integers(0, 4))]]
        s, t, e = (np.array(x) for x in zip(*rows))
        return kernel.Data(s, t, e, np.ones(len(s), np.int64), k, 3, 2)

    d = many(3000)
    m = kernel.Merger(d, kernel.Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne)))
    assert m.value[0].size <= 16
    for _ in range(6):
        d = many(14)
        p = kernel.Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne))
        a, b = kernel.greedy(d, p)[1], kernel.greedy_reference(d, p)[1]
        assert [x[:3] for x in a] == [x[:3] for x in b]


def test_moves_of_values_reach_a_local_optimum():
    """No single move lowers the cost any more, scored from scratch; a value's points are folded by cell."""
    rng = np.random.default_rng(12)
    cells, weight, edge = kernel._by_value(np.array([1, 0, 1, 1]), np.array([2, 0, 2, 1]), np.array([1, 2, 3, 4]), 3, 3)
    assert (cells.tolist(), weight.tolist(), edge) == ([0, 1, 2], [2, 4, 4], [0, 1, 3, 3])
    for _ in range(6):
        d = data(rng, ns=12)
        p = parts(rng, d, 4)
        kernel.improve_values(d, p, 0, rng, passes=50)
        now = kernel.total(d, p)
        for v in range(d.ns):
            for to in range(int(p.s.max()) + 1):
                q = kernel.Parts(p.s.copy(), p.t, p.e)
                q.s[v] = to
                assert kernel.total(d, q) >= now - 1e-6


def test_improvements_never_raise_the_cost():
    rng = np.random.default_rng(4)
    for _ in range(10):
        d = data(rng)
        for f in (lambda q: kernel.improve_values(d, q, 0, rng), lambda q: kernel.improve_values(d, q, 2, rng), lambda q: kernel.improve_bounds(d, q), lambda q: kernel.split_bounds(d, q)):
            p = parts(rng, d)
            before = kernel.total(d, p)
            n = f(p)
            after = kernel.total(d, p)
            assert after < before if n else after == pytest.approx(before)


def test_likelihood_alone_never_merges():
    rng = np.random.default_rng(5)
    d = data(rng)
    p = kernel.Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne))
    assert kernel.greedy(d, p, "likelihood")[1] == []


def test_toy_optimum_by_enumeration(spark):
    for repeats, best, shape in ((1, 85.888856, (1, 1, 1)), (2, 176.612587, (2, 2, 2))):
        top = baseline.exhaustive(workloads.toy(spark, repeats)).orderBy("rank").first()
        assert top["cost"] == pytest.approx(best, abs=1e-5) and (top["k_s"], top["k_t"], top["k_e"]) == shape
        g = fits.fit(workloads.toy(spark, repeats))
        assert score.cost(g) == pytest.approx(best, abs=1e-5)
    with pytest.raises(ValueError):
        baseline.exhaustive(workloads.toy(spark, 2), max_models=10)


def grid_of(spark, seed=6, n=300):
    rng = np.random.default_rng(seed)
    p = points.from_rows(spark, [(int(a), int(b), "abcde"[c]) for a, b, c in zip(rng.integers(0, 9, n), rng.integers(0, 30, n), rng.integers(0, 5, n))])
    return grid.lay(p, F.col("s") % 3, encode.interval_of(F.col("t"), [8, 17]), F.when(F.col("e") < "c", 0).otherwise(1))


def test_terms_levels_and_extremes(spark):
    g = grid_of(spark)
    t = score.cost(g)
    assert score.score_levels(g).agg(F.sum("value")).first()[0] == pytest.approx(t)
    assert score.split(g).agg(F.sum("value")).first()[0] == pytest.approx(t)
    assert score.bits(g) == pytest.approx(t / math.log(2))
    p = g.laid.select("s", "t", "e", "n")
    assert score.cost(grid.null(p)) == pytest.approx(score.null_cost(p))
    assert score.cost(grid.finest(p)) == pytest.approx(score.finest_cost(p))
    # labels, row order, and weights for repeated rows make no difference
    twice = points.fold(p.withColumn("n", F.col("n") * 2))
    again = points.fold(p.unionByName(p))
    q = lambda x: score.cost(grid.lay(x, 7 - F.col("s") % 3, encode.interval_of(F.col("t"), [8, 17]), F.when(F.col("e") < "c", 5).otherwise(1)))
    assert q(twice) == pytest.approx(q(again)) and q(p) == pytest.approx(t)
    # only the order of times counts
    assert score.cost(grid.lay(p.withColumn("t", F.col("t") * F.col("t") + 3), F.col("s") % 3, encode.interval_of(F.col("t"), [67, 292]), F.when(F.col("e") < "c", 0).otherwise(1))) == pytest.approx(t)


def test_dataframe_merges_and_moves_equal_rescoring(spark):
    g = grid_of(spark)
    now = score.cost(g)
    for r in merge.all_deltas(g).collect()[:6]:
        after = merge.apply(g, {r["dim"]: {r["right"]: r["left"]}})
        assert score.cost(after) - now == pytest.approx(r["delta"], abs=1e-7)
    moves = refine.move_deltas(g, "S").orderBy("value", "target").collect()
    for r in moves[:3]:
        laid = g.laid.withColumn("s_part", F.when(F.col("s") == r["value"], r["target"]).otherwise(F.col("s_part")))
        assert score.cost(grid.of_columns(laid)) - now == pytest.approx(r["delta"], abs=1e-7)
    for r in refine.boundary_deltas(g).orderBy("left", "t").collect()[:4]:
        part = F.when(F.col("t_part").isin(r["left"], r["left"] + 1), F.when(F.col("t") <= r["t"], r["left"]).otherwise(r["left"] + 1)).otherwise(F.col("t_part"))
        assert score.cost(grid.of_columns(g.laid.withColumn("t_part", part))) - now == pytest.approx(r["delta"], abs=1e-7)


def test_moving_a_lone_value_is_a_merge(spark):
    g = grid_of(spark)
    lone = grid.of_columns(g.laid.withColumn("e_part", F.when(F.col("e") == "a", 0).when(F.col("e") == "b", 1).otherwise(2)))
    m = {(r["left"], r["right"]): r["delta"] for r in merge.deltas(lone, "E").collect()}
    v = {(r["part"], r["target"]): r["delta"] for r in refine.move_deltas(lone, "E").where("part < 2").collect()}
    assert v[0, 1] == pytest.approx(m[0, 1]) and v[1, 0] == pytest.approx(m[0, 1]) and v[1, 2] == pytest.approx(m[1, 2])


def test_distributed_refinement_lowers_the_cost(spark):
    p = synth.two_patterns(spark, 3000, 5, 0.1, seed=3)
    g = grid.lay(p, F.when(F.col("s") < 8, F.col("s") % 2).otherwise(0), encode.interval_of(F.col("t"), [130, 230, 390, 480, 620, 730]), F.floor(F.col("e") / 3))
    h, n = refine.move_values(g, "S")
    assert n and score.cost(h) < score.cost(g) and accuracy.ari(h.s_values, workloads.truth_of_users(p)).first()[0] == 1
    k, n = refine.move_bounds(h)
    assert n and score.cost(k) < score.cost(h)


def test_batched_merging_is_exact_and_close(spark):
    p = synth.two_patterns(spark, 4000, 5, 0.0, seed=4)
    start = fits.coarse_grid(p, cap=12)
    g, log = fits.greedy_batched(start)
    assert score.cost(g) - score.cost(start) == pytest.approx(sum(x[3] for x in log), abs=1e-5)
    assert accuracy.ari(g.s_values, workloads.truth_of_users(p)).first()[0] == 1


def test_fit_beyond_a_task(spark):
    p = synth.two_patterns(spark, 3000, 5, 0.1, seed=5)
    want = score.cost(fits.fit(p, rounds=4))
    for most in (2500, 100):  # a task that holds the points once time is cut coarsely, and one that holds no points
        g = fits.fit(p, rounds=4, max_kernel_points=most)
        assert accuracy.ari(g.s_values, workloads.truth_of_users(p)).first()[0] == 1
        assert score.cost(g) <= want + 1e-6


def test_fit_finds_planted_patterns_and_nothing_in_noise(spark):
    p = synth.two_patterns(spark, 4096, 10, 0.3, seed=6)
    log, g = fits.restarts(p, 6)
    assert accuracy.ari(g.s_values, workloads.truth_of_users(p)).first()[0] == 1
    assert score.cost(g) <= min(score.cost(synth.truth_grid(p)), score.null_cost(p)) + 1e-6
    best = [r["best_so_far"] for r in log.orderBy("round").collect()]
    assert best == sorted(best, reverse=True) and best[-1] == pytest.approx(score.cost(g))
    found = g.t_parts.where(F.col("t_part") < g.shape().kT - 1).select(F.col("t_hi").alias("cut"))
    r = accuracy.cut_recovery(found, spark.createDataFrame([(float(c),) for c in workloads.TRUE_CUTS], "cut double"), 15).first()
    assert r["precision"] == 1 and r["recall"] == 1
    noise = p.withColumn("e", (F.xxhash64("s", "t") % 6).cast("int"))
    assert fits.fit(noise, rounds=4).shape().k == 1
    log, better = fits.neighbourhood(p, synth.truth_grid(p), 4)
    assert score.cost(better) <= score.cost(synth.truth_grid(p)) + 1e-6


def test_splits_are_exact_and_bring_bounds_back(spark):
    p = synth.two_patterns(spark, 3000, 5, 0.1, seed=11)
    g = grid.lay(p, F.col("s") % 2, F.lit(0), F.floor(F.col("e") / 3))
    now = score.cost(g)
    step = merge.variable_step(g, "T", -1)
    for r in refine.split_deltas(g).orderBy(F.xxhash64("t")).limit(3).collect():
        assert score.cost(refine._labelled(g, [r["t"]])) - now == pytest.approx(r["delta"] + step, abs=1e-6)
    h, n = refine.split_intervals(g)
    assert n >= 6 and score.cost(refine.move_bounds(h)[0]) <= score.cost(synth.truth_grid(p)) + 1e-6


def test_quantiles_follow_the_weights(spark):
    p = spark.createDataFrame([("a", t, "x", 9 if t < 10 else 1) for t in range(100)], "s string, t int, e string, n long")
    exact, quick = encode.quantile_cuts(p, 4, exact=True), encode.quantile_cuts(p, 4)
    assert all(abs(a - b) <= 1 for a, b in zip(exact, quick)) and quick[0] < 10


def test_hierarchy(spark):
    p = synth.two_patterns(spark, 3000, 5, 0.1, seed=7)
    g = synth.truth_grid(p)
    m = hierarchy.build(g)
    rows = m.orderBy("step").collect()
    assert len(rows) == 1 + 6 + 3 and rows[-1]["cost"] == pytest.approx(score.null_cost(p), abs=1e-5) and rows[-1]["info_ratio"] == pytest.approx(0, abs=1e-9)
    assert rows[0]["delta"] == pytest.approx(merge.all_deltas(g).agg(F.min("delta")).first()[0], abs=1e-6)
    half = hierarchy.cut(g, m, k_t=4)
    assert half.shape().kT == 4
    step = next(i for i, r in enumerate(rows) if r["k_t"] == 4)
    assert score.cost(half) == pytest.approx(rows[step]["cost"], abs=1e-5)
    kept = hierarchy.cut(g, m, min_info=0.7)
    assert score.cost(kept) == pytest.approx([r["cost"] for r in rows if r["info_ratio"] >= 0.7][-1], abs=1e-5)
    tree = hierarchy.tree(m, "T").collect()
    assert len(tree) == 12 and sum(r["node"].endswith("@-1") for r in tree) == 7
    flat = hierarchy.build(grid.null(p))
    assert flat.count() == 0


def test_views(spark):
    g = synth.truth_grid(synth.two_patterns(spark, 40_000, 5, 0.5, seed=8))
    for focus in "STE":
        assert insight.mutual_information(g, focus).agg(F.min("mi")).first()[0] > -1e-12
        assert insight.contrast(g, focus).first()[0] > -1e-12
    signs = {(r["focus"], r["row"], r["col"]): r["contrast"] for r in insight.contrast_cells(g).collect()}
    assert abs(signs[0, 0, 2]) < 0.004 and abs(signs[0, 3, 1]) < 0.004 and signs[0, 0, 0] > 0 > signs[1, 0, 0]
    t = typical.typicality(g, "S").collect()
    assert all(r["tau"] > 0 for r in t)
    one = typical.typicality(grid.null(g.laid.select("s", "t", "e", "n")), "S").collect()
    assert all(r["tau"] is None for r in one)
    assert {r["dim"] for r in insight.describe(g).collect()} == {"S", "T", "E"}
    p = insight.density(g).agg(F.sum("p")).first()[0]
    assert p == pytest.approx(1)


def brute_ari(a, b):
    n = len(a)
    pairs = list(itertools.combinations(range(n), 2))
    same = lambda x: {q for q in pairs if x[q[0]] == x[q[1]]}
    i, j = same(a), same(b)
    e = len(i) * len(j) / len(pairs)
    top = (len(i) + len(j)) / 2
    return 1.0 if top == e else (len(i & j) - e) / (top - e)


def test_adjusted_rand_index(spark):
    rng = np.random.default_rng(9)
    for a, b in [(rng.integers(0, 3, 20).tolist(), rng.integers(0, 4, 20).tolist()) for _ in range(2)] + [([0] * 5, [1] * 5), ([0] * 6, [0, 1] * 3), ([0, 1, 2], [2, 0, 1])]:
        p = spark.createDataFrame(list(enumerate(a)), "value int, part int")
        t = spark.createDataFrame(list(enumerate(b)), "value int, label int")
        assert accuracy.ari(p, t).first()[0] == pytest.approx(brute_ari(a, b))


def test_sources(spark, tmp_path):
    rows = [(1, 5, "a"), (1, 5, "a"), (None, 1, "b"), (2, None, "a"), (2, 7, None), (2, 7, "é")]
    df = spark.createDataFrame(rows, "k int, t int, e string")
    p = points.from_table(df, "k", "t", "e")
    assert {tuple(r) for r in p.collect()} == {(1, 5, "a", 2), (2, 7, "é", 1)} and points.dropped_points(df, "k", "t", "e").first()[0] == 3
    assert {tuple(r) for r in points.from_nested(points.to_nested(p), "s", "obs").collect()} == {tuple(r) for r in p.collect()}
    for fmt in ("csv", "json", "orc", "parquet"):
        persist.export(df, str(tmp_path / fmt), fmt)
        got = points.read(spark, fmt, str(tmp_path / fmt), "k", "t", "e", schema="k int, t int, e string")
        assert {tuple(r) for r in got.collect()} == {tuple(r) for r in p.collect()}
    g = grid_of(spark)
    persist.save(g, str(tmp_path / "grid"))
    assert score.cost(persist.load(spark, str(tmp_path / "grid"))) == pytest.approx(score.cost(g))
    empty = points.from_table(df.limit(0), "k", "t", "e")
    assert score.cost(grid.null(empty)) == 0 and score.null_cost(empty) == 0
    assert points.subset(spark.range(1000), "id", 10).agg(F.max("id")).first()[0] > 500


def test_edges(spark):
    for rows in ([(1, 1, "a")], [(1, 1, "a"), (1, 1, "a")], [(1, t, "a") for t in range(5)], [(s, 1, "ab"[s % 2]) for s in range(6)], [(1, -t, "é") for t in range(3)]):
        p = points.from_rows(spark, rows)
        g = fits.fit(p, rounds=2)
        assert score.cost(g) <= score.null_cost(p) + 1e-9 and g.cells.agg(F.sum("n")).first()[0] == len(rows)
    p = points.from_rows(spark, [("x", 1, "a"), ("y", 2, "b")], "s string, t int, e string")
    assert fits.fit(p, rounds=2).shape().n == 2


def test_encode(spark):
    df = spark.range(500).select(F.pmod(F.col("id") * 7919, F.lit(1009)).alias("x"))
    ids = encode.ordered_ids(df, "x").orderBy("x").collect()
    assert [r["id"] for r in ids] == list(range(500))
    cuts = list(range(0, 1000, 5))
    a = spark.range(-3, 1005).select("id", encode.interval_of(F.col("id"), cuts).alias("a"), encode.lookup_interval(F.col("id"), cuts).alias("b"))
    assert a.where("a <> b").count() == 0 and a.where("id = 5").first()["a"] == 1 and a.where("id = 6").first()["a"] == 2


def test_assignment(spark):
    p = synth.two_patterns(spark, 4000, 10, 0.2, seed=10)
    g = synth.truth_grid(p.where("s < 14"))
    got = assign.nearest(g, p.where("s >= 14")).collect()
    assert len(got) == 6 and all(r["part"] == r["s"] % 2 for r in got)
    assert {tuple(r) for r in assign.unseen(g, p.where("s >= 14")).collect()} == {("S", str(s)) for s in range(14, 20)}


@pytest.mark.parametrize("aqe", ["true", "false"])
def test_grids_of_laid_points_with_ordered_ids(spark, aqe):
    """finest, coarse_grid and dictionary take points whose lineage they join back to."""
    before = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", aqe)
    try:
        g = grid_of(spark, seed=12)
        p = g.laid.select("s", "t", "e", "n")
        fine = grid.finest(p)
        h = fine.shape()
        assert (h.kS, h.kE) == (h.n, h.a) and score.cost(fine) == pytest.approx(score.finest_cost(p))
        assert fine.t_parts.where("t_lo <> t_hi").count() == 0
        coarse = fits.coarse_grid(persist.cut(p), cap=6)
        assert coarse.cells.agg(F.sum("n")).first()[0] == h.N
        assert [r["id"] for r in points.dictionary(p, "t").orderBy("value").collect()] == list(range(h.kT))
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", before)


def test_merges_of_intervals_leave_the_rest_in_place(monkeypatch):
    """Two thousand single times: the arrays are copied when half of the intervals are gone, not at every merge."""
    n = 2000
    d = kernel.Data(np.arange(n) % 3, np.arange(n), np.arange(n) % 4, np.ones(n, int), 3, n, 4)
    calls, delete = [0], np.delete
    monkeypatch.setattr(kernel.np, "delete", lambda *a, **k: (calls.__setitem__(0, calls[0] + 1), delete(*a, **k))[1])
    p, path, m = kernel.greedy(d, kernel.Parts(np.arange(3), np.arange(n), np.arange(4)))
    assert m.merges > 1000 and calls[0] < 100
    assert sum(x[3] for x in path) == pytest.approx(kernel.total(d, p) - kernel.total(d, kernel.Parts(np.arange(3), np.arange(n), np.arange(4))), abs=1e-6)


def test_splits_look_again_at_two_sides_only(monkeypatch):
    """Ten planted bounds are found with few more points sorted than there are; no further cut lowers the cost."""
    n, parts_ = 4000, 10
    t = np.arange(n)
    e = (t * parts_ // n) % 2 * 2 + t % 2
    d = kernel.Data(np.zeros(n, int), t, e, np.ones(n, int), 1, n, 4)
    p = kernel.Parts(np.zeros(1, int), t * 5 // n, np.arange(4))
    seen, sort = [0], np.argsort

    def counted(x, *a, **k):
        seen[0] += len(x)
        return sort(x, *a, **k)

    monkeypatch.setattr(kernel.np, "argsort", counted)
    before = kernel.total(d, p)
    seen[0] = 0
    assert kernel.split_bounds(d, p) == 5 and seen[0] <= 2 * n + 100
    monkeypatch.undo()
    assert p.t.max() == 9 and (np.bincount(p.t) == 400).all() and kernel.total(d, p) < before
    assert all(kernel.total(d, kernel.Parts(p.s, p.t + (t > c), p.e)) >= kernel.total(d, p) - 1e-6 for c in range(0, n - 1, 97) if p.t[c] == p.t[c + 1])


def test_sweep_plants_the_same_points_in_a_task(spark, sf):
    """The rows that a task plants from packed blocks are those of the points table, for every set; no points are exchanged."""
    from seqgrid import queries

    want = {}
    for r in workloads.sweep_points(spark, sf, (10, 50), (0.0, 0.3)).collect():
        want.setdefault((r["cm"], r["eta"], r["size"]), []).append((r["s"], r["t"], r["e"], r["n"]))
    rows = workloads.unpacked([bytes(r["block"]) for r in workloads.packed_carrier(spark, sf, 100).collect()])
    assert len(want) == 4 * 5 and len(rows) == 1000
    for (cm, eta, size), points_ in want.items():
        got = zip(*(x.tolist() for x in workloads.planted_rows(rows[:size], cm, eta)))
        assert sorted(got) == sorted(points_)
    swept = queries.sweep(spark, sf, (10,), (0.0,), 2)
    plan = swept._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and plan.count("Exchange") <= 2
    assert {r["N"] for r in swept.collect()} == {64, 128, 256, 512, 1000}


def test_a_fit_with_time_cut_first_keeps_its_options(spark, monkeypatch):
    p = points.from_rows(spark, [(i % 3, i, "ab"[i % 2]) for i in range(600)])
    seen, real = [], fits.restarts
    monkeypatch.setattr(fits, "CAP", 16)
    monkeypatch.setattr(fits, "restarts", lambda *a, **k: (seen.append((a[0].count(), k)), real(*a, **k))[1])
    g = fits.fit(p, rounds=1, start="finest", pre=False, post=False, max_kernel_points=200)
    assert g.shape().N == 600 and seen[0][0] <= 200
    assert (seen[0][1]["start"], seen[0][1]["pre"], seen[0][1]["post"]) == ("finest", False, False)


def test_a_start_holds_few_bytes_a_point(monkeypatch):
    """Points are kept in 16 bytes, and moves of values and shifts and splits of bounds work on blocks of them."""
    import tracemalloc

    monkeypatch.setattr(kernel, "BLOCK", 1 << 14)
    n, rng = 400_000, np.random.default_rng(21)
    d = kernel.Data(rng.integers(0, 50, n), np.arange(n) // 4, rng.integers(0, 5, n), np.ones(n, int), 50, n // 4, 5)
    assert sum(x.nbytes for x in (d.s, d.t, d.e, d.n)) == 16 * n
    p = kernel.random_start(d, np.random.default_rng(2))
    steps = (lambda: kernel.improve_values(d, p, 0, rng, 1), lambda: kernel.improve_values(d, p, 2, rng, 1), lambda: kernel.improve_bounds(d, p, 1), lambda: kernel.split_bounds(d, kernel.null_parts(d)), lambda: kernel.total(d, p))
    for step in steps:
        tracemalloc.start()
        step()
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert peak <= 48 * n


def test_starts_read_packed_points(spark):
    """Blocks of points give the codes that the points as one table give, and no start's points are exchanged."""
    rows = [(f"u{i % 7}", i // 3, "xyz"[i * i % 3]) for i in range(300)]
    p = points.from_rows(spark, rows, "s string, t int, e string")
    blocks = [bytes(r["block"]) for r in fits._packed(p.select(*"sten")).collect()]
    d, *values = fits.data_of_blocks(blocks, "at_most")
    w, *want = fits.data_of(p.toPandas(), "at_most")
    assert [x.tolist() for x in values] == [x.tolist() for x in want]
    assert sorted(zip(d.s, d.t, d.e, d.n)) == sorted(zip(w.s, w.t, w.e, w.n))
    runs = fits.run_rounds(p, 3)
    plan = runs._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan
    assert sorted(r["round"] for r in runs.collect()) == [0, 1, 2]


def test_moves_of_a_profile_that_a_task_holds(spark, monkeypatch):
    """One task makes them one after the other, to an optimum of single moves; the points carry the same parts."""
    p = synth.two_patterns(spark, 3000, 5, 0.1, seed=5).withColumn("s", F.concat(F.lit("u"), "s"))
    g = grid.lay(p, F.pmod(F.xxhash64("s"), F.lit(3)), encode.interval_of(F.col("t"), [100, 250, 400, 500, 600, 750]), F.floor(F.col("e") / 3))
    monkeypatch.setattr(refine, "move_values", None)  # no pass over all values at once is needed
    h, n = fits.move_values(g, "S")
    assert n and score.cost(h) < score.cost(g)
    assert score.cost(grid.of_columns(h.laid)) == pytest.approx(score.cost(h), abs=1e-6)
    assert refine.move_deltas(h, "S").agg(F.min("delta")).first()[0] >= -1e-6
    assert fits.move_values(h, "S")[1] == 0


def test_bounds_that_a_task_holds(spark):
    """Bounds shift and split to where no single shift or split lowers the cost, as the passes over all points find them."""
    p = synth.two_patterns(spark, 3000, 5, 0.1, seed=11)
    g = grid.lay(p, F.col("s") % 2, encode.interval_of(F.col("t"), [130, 480]), F.floor(F.col("e") / 3))
    h, n = fits.move_bounds(g)
    assert n and score.cost(h) < score.cost(g) and score.cost(h) <= score.cost(synth.truth_grid(p)) + 1e-6
    assert refine.boundary_deltas(h).agg(F.min("delta")).first()[0] >= -1e-6
    assert refine.split_deltas(h).agg(F.min("delta")).first()[0] + merge.variable_step(h, "T", -1) >= -1e-6
    assert fits.move_bounds(h)[1] == 0
