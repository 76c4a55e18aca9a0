"""Views of a grid with any axis in focus: frequency, contribution to mutual information, contrast, density."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqgrid.operators.grid import DIMS, Grid

VIEW = {"S": ("t_part", "e_part"), "T": ("s_part", "e_part"), "E": ("s_part", "t_part")}


def view(g: Grid, focus: str = "S") -> DataFrame:
    """(focus, row, col, freq)."""
    row, col = VIEW[focus]
    return g.cells.select(F.col(DIMS[focus]).alias("focus"), F.col(row).alias("row"), F.col(col).alias("col"), F.col("n").alias("freq"))


def cmi(g: Grid, focus: str = "S") -> DataFrame:
    """(focus, row, col, freq, cmi): each cell's part of the mutual information of the two other axes within the focus cluster."""
    over = lambda *c: F.sum("freq").over(Window.partitionBy(*c))
    v = view(g, focus).withColumn("f", over("focus")).withColumn("r", over("focus", "row")).withColumn("c", over("focus", "col"))
    p = F.col("freq") / F.col("f")
    return v.select("focus", "row", "col", "freq", (p * F.log(F.col("freq") * F.col("f") / (F.col("r") * F.col("c")))).alias("cmi"))


def mutual_information(g: Grid, focus: str = "S") -> DataFrame:
    return cmi(g, focus).groupBy("focus").agg(F.sum("cmi").alias("mi"))


def contrast_cells(g: Grid, focus: str = "S") -> DataFrame:
    """(focus, row, col, freq, contrast): each cell's part of the mutual information of (row, col) jointly with the focus axis."""
    N = F.lit(float(max(g.shape().N, 1)))
    v = view(g, focus).withColumn("rc", F.sum("freq").over(Window.partitionBy("row", "col"))).withColumn("f", F.sum("freq").over(Window.partitionBy("focus")))
    return v.select("focus", "row", "col", "freq", (F.col("freq") / N * F.log(F.col("freq") * N / (F.col("rc") * F.col("f")))).alias("contrast"))


def contrast(g: Grid, focus: str = "S") -> DataFrame:
    return contrast_cells(g, focus).agg(F.coalesce(F.sum("contrast"), F.lit(0.0)).alias("contrast"))


def sign(value: Column, eps: float = 1e-3) -> Column:
    """Colour class of a measure; null stands for an empty cell."""
    return F.when(value.isNull(), "empty").when(value > eps, "excess").when(value < -eps, "deficit").otherwise("as expected")


def full_matrix(measured: DataFrame, measure: str) -> DataFrame:
    """All (focus, row, col), empty cells with a null measure."""
    axis = lambda c: measured.select(c).distinct()
    return axis("focus").crossJoin(axis("row")).crossJoin(axis("col")).join(measured.select("focus", "row", "col", measure), ["focus", "row", "col"], "left")


def matrix(measured: DataFrame, value: str) -> DataFrame:
    """(focus, row) by columns c<col>."""
    wide = measured.withColumn("c", F.concat(F.lit("c"), F.col("col"))).groupBy("focus", "row").pivot("c").agg(F.first(value))
    return wide


def cells_of(wide: DataFrame, value: str) -> DataFrame:
    """matrix() undone: (focus, row, col, value) of the cells that aren't null."""
    columns = [c for c in wide.columns if c not in ("focus", "row")]
    long = wide.unpivot(["focus", "row"], columns, "c", value).where(F.col(value).isNotNull())
    return long.select("focus", "row", F.substring("c", 2, 10).cast("int").alias("col"), value)


def density(g: Grid) -> DataFrame:
    """(s_part, t_part, e_part, p, density): the cell's probability, and that over interval width and cluster sizes; width 0 counts 1."""
    N = F.lit(float(max(g.shape().N, 1)))
    t = g.t_parts.select("t_part", F.greatest(F.col("t_hi").cast("double") - F.col("t_lo").cast("double"), F.lit(0.0)).alias("w"))
    size = lambda d, c: g.parts(d).select(F.col("part").alias(c), F.col("n_values").alias("m_" + d))
    x = g.cells.join(F.broadcast(t), "t_part").join(F.broadcast(size("S", "s_part")), "s_part").join(F.broadcast(size("E", "e_part")), "e_part")
    p = F.col("n") / N
    return x.select("s_part", "t_part", "e_part", p.alias("p"), (p / (F.when(F.col("w") > 0, F.col("w")).otherwise(1.0) * F.col("m_S") * F.col("m_E"))).alias("density"))


def marginals(g: Grid) -> DataFrame:
    """All eight marginals at once: (s_part, t_part, e_part, gid, n); gid tells which coordinates are summed over."""
    return g.cells.cube("s_part", "t_part", "e_part").agg(F.grouping_id().cast("int").alias("gid"), F.sum("n").cast("long").alias("n"))


def rollup(g: Grid) -> DataFrame:
    return g.cells.rollup("s_part", "t_part", "e_part").agg(F.grouping_id().cast("int").alias("gid"), F.sum("n").cast("long").alias("n"))


def top_cells(measured: DataFrame, measure: str, k: int = 10) -> DataFrame:
    return measured.orderBy(F.abs(measure).desc(), "focus", "row", "col").limit(k)


def describe(g: Grid, k: int = 3) -> DataFrame:
    """(dim, part, n_points, n_values, t_lo, t_hi, typical, strongest): one row for each part of the grid."""
    from seqgrid.operators.typical import top

    t = g.t_parts.select(F.lit("T").alias("dim"), F.col("t_part").alias("part"), F.col("n").alias("n_points"), F.lit(1).cast("long").alias("n_values"), F.col("t_lo").cast("string").alias("t_lo"), F.col("t_hi").cast("string").alias("t_hi"))
    none = F.lit(None).cast("string")
    rows = t
    typical = None
    for dim in ("S", "E"):
        rows = rows.unionByName(g.parts(dim).select(F.lit(dim).alias("dim"), "part", "n_points", "n_values", none.alias("t_lo"), none.alias("t_hi")))
        x = top(g, dim, k).groupBy("dim", "part").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", F.col("value").cast("string").alias("v")))), lambda y: y["v"]).alias("typical"))
        typical = x if typical is None else typical.unionByName(x)
    cells = None
    for dim in DIMS:
        w = Window.partitionBy("focus").orderBy(F.abs("contrast").desc(), "row", "col")
        x = contrast_cells(g, dim).withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).groupBy("focus").agg(F.transform(F.array_sort(F.collect_list(F.struct("r", "row", "col"))), lambda y: F.concat_ws("x", y["row"], y["col"])).alias("strongest")).select(F.lit(dim).alias("dim"), F.col("focus").alias("part"), "strongest")
        cells = x if cells is None else cells.unionByName(x)
    return rows.join(typical, ["dim", "part"], "left").join(cells, ["dim", "part"], "left")
