"""The cost of a grid, by term and by level; compression; closed forms of the two extreme grids."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqgrid.functions.mathx import lf, lg, ln_b, ln_fact, variable_level
from seqgrid.operators.grid import Grid

PRIOR = ("shape", "cell_freq_prior", "seq_freq_prior", "event_freq_prior")
LIKELIHOOD = ("cell_lik", "seq_lik", "event_lik", "time_rank_lik")


def _terms(g: Grid) -> dict[str, float]:
    h, x = g.shape(), g.sums()
    if h.N == 0:
        return dict.fromkeys((*PRIOR, *LIKELIHOOD), 0.0)
    S, E, T, C = (x[d] for d in "SETC")
    return {
        "shape": math.log(h.n) + math.log(h.a) + math.log(h.N) + ln_b(h.n, h.kS, g.prior) + ln_b(h.a, h.kE, g.prior),
        "cell_freq_prior": lg(h.N + h.k) - lg(h.k) - lf(h.N),
        "seq_freq_prior": S["step"] - S["parts"],
        "event_freq_prior": E["step"] - E["parts"],
        "cell_lik": lf(h.N) - C["values"],
        "seq_lik": S["parts"] - S["values"],
        "event_lik": E["parts"] - E["values"],
        "time_rank_lik": T["values"],
    }


def score_terms(g: Grid) -> DataFrame:
    """(term, value), eight rows: four of the prior, four of the likelihood. An empty grid costs 0 in each."""
    return g.laid.sparkSession.createDataFrame([(t, float(v)) for t, v in _terms(g).items()], "term string, value double")


def score_levels(g: Grid) -> DataFrame:
    """(level, dim, value): constant, variable, part (by dimension) and cell; they add up to the cost."""
    h, x = g.shape(), g.sums()
    rows = []
    if h.N:
        constant = math.log(h.n) + math.log(h.a) + math.log(h.N) + lf(h.N) - x["S"]["values"] - x["E"]["values"]
        rows = [("constant", "all", constant), ("variable", "all", variable_level(h.n, h.a, h.N, h.kS, h.kT, h.kE, g.prior)), ("part", "S", x["S"]["step"]), ("part", "E", x["E"]["step"]), ("part", "T", x["T"]["values"]), ("cell", "all", -x["C"]["values"])]
    return g.laid.sparkSession.createDataFrame([(a, b, float(v)) for a, b, v in rows], "level string, dim string, value double")


def cost(g: Grid) -> float:
    return sum(_terms(g).values())


def bits(g: Grid) -> float:
    return cost(g) / math.log(2)


def split(g: Grid) -> DataFrame:
    """(side, value): prior and likelihood."""
    return score_terms(g).groupBy(F.when(F.col("term").isin(*PRIOR), "prior").otherwise("likelihood").alias("side")).agg(F.sum("value").alias("value"))


def likelihood_only(g: Grid) -> float:
    terms = _terms(g)
    return sum(terms[t] for t in LIKELIHOOD)


def _marginals(points: DataFrame) -> tuple[int, int, int, float, float]:
    """n, a, N and the sums of ln n! over sequences and over events, by one job."""
    both = points.groupingSets([[F.col("s")], [F.col("e")]], F.col("s"), F.col("e")).agg(F.grouping_id().alias("gid"), F.sum("n").cast("long").alias("n"))
    got = {r["gid"]: r for r in both.groupBy("gid").agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("N"), F.sum(ln_fact(F.col("n"))).alias("l")).collect()}
    if not got:
        return 0, 0, 0, 0.0, 0.0
    s, e = got[1], got[2]  # 1: e summed over; 2: s summed over
    return int(s["k"]), int(e["k"]), int(s["N"]), s["l"], e["l"]


def null_cost(points: DataFrame) -> float:
    """Cost of the single cell, from the marginals alone."""
    n, a, big, ls, le = _marginals(points)
    if not big:
        return 0.0
    head = math.log(n) + math.log(a) + math.log(big)
    return head + lg(big + n) - lg(n) + lg(big + a) - lg(a) - ls - le + lf(big)


def finest_cost(points: DataFrame, prior: str = "at_most") -> float:
    """Cost of the grid in which every value is a part, without building it."""
    n, a, big, ls, le = _marginals(points)
    if not big:
        return 0.0
    cells = points.groupBy("s", "t", "e").agg(F.sum("n").alias("n")).agg(F.sum(ln_fact(F.col("n")))).first()[0]
    t = points.groupBy("t").agg(F.sum("n").alias("n")).agg(F.sum(ln_fact(F.col("n"))).alias("l"), F.count(F.lit(1)).alias("k")).first()
    k = float(n) * a * t["k"]
    # a part of one value has no inner frequencies to tell: lnC(N, 0) = 0, and ln N_c! - ln n_i! = 0
    return math.log(n) + math.log(a) + math.log(big) + ln_b(n, n, prior) + ln_b(a, a, prior) + lg(big + k) - lg(k) - lf(big) + lf(big) - cells + t["l"]


def compression(cost_value: float, null_value: float) -> float:
    """Share of the null grid's code length that is saved."""
    return 0.0 if not null_value else 1 - cost_value / null_value
