"""The SQL surface: scalar functions, the five marginals by grouping sets, label replay by recursion, table functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

_FUNCTIONS = {
    # bodies are inlined by Spark: no call at run time
    "ln_fact(x BIGINT)": "CASE WHEN x < 18 THEN element_at(array({small}), CAST(x AS INT) + 1) ELSE (x + 0.5D) * ln(x) - x + {half}D + (1.0D / 12 - (1.0D / 360 - (1.0D / 1260 - 1.0D / 1680 / x / x) / x / x) / x / x) / x END",
    "ln_gamma(x BIGINT)": "ln_fact(x - 1)",
    "ln_binom(n BIGINT, k BIGINT)": "ln_fact(n) - ln_fact(k) - ln_fact(n - k)",
    "cmi_term(n DOUBLE, row_n DOUBLE, col_n DOUBLE, all_n DOUBLE)": "CASE WHEN n > 0 THEN n / all_n * ln(n * all_n / (row_n * col_n)) ELSE 0.0D END",
}


def register(spark: SparkSession) -> None:
    """ln_fact, ln_gamma, ln_binom and cmi_term as temporary SQL functions; grid_fit and merge_path as table functions."""
    import math

    small = ", ".join(f"{math.lgamma(i + 1)!r}D" for i in range(18))
    for head, body in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS DOUBLE RETURN {body.format(small=small, half=repr(0.5 * math.log(2 * math.pi)))}")
    spark.udtf.register("grid_fit", GridFit)
    spark.udtf.register("merge_path", MergePath)


def five_marginals(cells: DataFrame) -> DataFrame:
    """Just the marginals that the views need, in one aggregation."""
    cells.createOrReplaceTempView("_grid_cells")
    return cells.sparkSession.sql("""
        SELECT s_part, t_part, e_part, CAST(grouping_id() AS INT) AS gid, CAST(sum(n) AS BIGINT) AS n FROM _grid_cells
        GROUP BY s_part, t_part, e_part GROUPING SETS ((t_part, e_part), (s_part), (s_part, t_part), (s_part, e_part), ())""")


def replay(merges: DataFrame, dim: str, upto: int, parts: DataFrame) -> DataFrame:
    """(part, label): each part's group after the steps below upto, by a recursive query over the merges."""
    merges.where((F.col("dim") == dim) & (F.col("step") < upto)).select("left", "right").createOrReplaceTempView("_grid_merges")
    parts.select("part").distinct().createOrReplaceTempView("_grid_parts")
    return merges.sparkSession.sql("""
        WITH RECURSIVE up (part, label, depth) AS (
            SELECT part, part AS label, 0 AS depth FROM _grid_parts
            UNION ALL
            SELECT up.part, m.left AS label, up.depth + 1 FROM up JOIN _grid_merges m ON up.label = m.right)
        SELECT part, min_by(label, -depth) AS label FROM up GROUP BY part""")


class _Points:
    """Collects the rows (s, t, e, n) of its partition."""

    def __init__(self) -> None:
        self.rows: list[tuple] = []

    def eval(self, row) -> None:  # noqa: ANN001
        self.rows.append((str(row["s"]), float(row["t"]), str(row["e"]), int(row["n"])))

    def data(self):  # noqa: ANN202
        import pandas as pd

        from seqgrid.plans.fit import data_of

        return data_of(pd.DataFrame(self.rows, columns=["s", "t", "e", "n"]), "at_most")


@udtf(returnType="dim string, value string, part int, cost double")
class GridFit(_Points):
    """grid_fit(TABLE(points)): the best grid of ten starts, a row for each value of S and E and for each interval's end."""

    def terminate(self):  # noqa: ANN201
        if not self.rows:
            return
        import numpy as np

        from seqgrid.plans import kernel

        d, sv, tv, ev = self.data()
        r = min((kernel.one_round(d, i, 0) for i in range(10)), key=lambda x: x.cost)
        for dim, values, label in (("S", sv, r.parts.s), ("E", ev, r.parts.e)):
            for v, k in zip(values, label):
                yield dim, str(v), int(k), float(r.cost)
        for k, end in enumerate([*np.flatnonzero(np.diff(r.parts.t)), len(tv) - 1]):
            yield "T", repr(float(tv[end])), k, float(r.cost)


@udtf(returnType="step int, dim string, left int, right int, delta double")
class MergePath(_Points):
    """merge_path(TABLE(points)): greedy merges from the coarse start."""

    def terminate(self):  # noqa: ANN201
        if not self.rows:
            return
        from seqgrid.plans import kernel

        d, *_ = self.data()
        for i, (dim, left, right, delta) in enumerate(kernel.greedy(d, kernel.coarse(d))[1]):
            yield i, "STE"[dim], int(left), int(right), float(delta)
