"""A grid: the points laid on three partitions, its sparse cells and the sizes of its parts."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqgrid.functions.encode import MAX_LITERAL_CUTS, interval_of, lookup_interval
from seqgrid.functions.mathx import ln_fact, ln_gamma_step

DIMS = {"S": "s_part", "T": "t_part", "E": "e_part"}
VALUE = {"S": "s", "E": "e"}


@dataclass(frozen=True)
class Shape:
    n: int  # sequences
    a: int  # event values
    N: int  # points
    kS: int
    kT: int
    kE: int

    @property
    def k(self) -> float:
        return float(self.kS) * self.kT * self.kE


@dataclass
class Grid:
    """cells (s_part, t_part, e_part, n); s_values and e_values (value, part, n); t_parts (t_part, n, t_lo, t_hi); laid: points with their parts; base: laid by sequence, interval and event."""

    laid: DataFrame
    cells: DataFrame
    s_values: DataFrame
    e_values: DataFrame
    t_parts: DataFrame
    prior: str = "at_most"
    cuts: list | None = None
    base: DataFrame | None = None
    _sums: dict | None = field(default=None, repr=False)

    def values(self, dim: str) -> DataFrame:
        return {"S": self.s_values, "E": self.e_values}[dim]

    def parts(self, dim: str) -> DataFrame:
        """(part, n_points, n_values) of a dimension; for T n_values is 1."""
        if dim == "T":
            return self.t_parts.select(F.col("t_part").alias("part"), F.col("n").alias("n_points"), F.lit(1).cast("long").alias("n_values"))
        return self.values(dim).groupBy("part").agg(F.sum("n").cast("long").alias("n_points"), F.count(F.lit(1)).alias("n_values"))

    def sums(self) -> dict:
        """What the cost is made of, by one job over the profile; kept. Four sets of coordinates are summed at once, then by part, then over the parts.

        For S and E: k parts, m values, N points, values' and parts' sums of ln n!, and step, the parts' ln Gamma(N + m) - ln Gamma(m); for T and the cells k, N and the sum of ln n!.
        """
        if self._sums is None:
            base = profile(self.laid) if self.base is None else self.base
            keys = ["s", "s_part", "t_part", "e", "e_part"]
            sets = {"S": ("s", "s_part"), "E": ("e", "e_part"), "C": ("s_part", "t_part", "e_part"), "T": ("t_part",)}
            gid = {sum(1 << (len(keys) - 1 - i) for i, k in enumerate(keys) if k not in v): d for d, v in sets.items()}
            one = base.groupingSets([[F.col(c) for c in v] for v in sets.values()], *[F.col(c) for c in keys]).agg(F.grouping_id().alias("gid"), F.sum("n").cast("long").alias("n"))
            code = {d: g for g, d in gid.items()}
            part = F.when(F.col("gid") == code["S"], F.col("s_part")).when(F.col("gid") == code["E"], F.col("e_part"))
            two = one.groupBy("gid", part.alias("part")).agg(F.count(F.lit(1)).alias("m"), F.sum("n").cast("long").alias("N"), F.sum(ln_fact(F.col("n"))).alias("values"))
            rows = two.groupBy("gid").agg(F.count(F.lit(1)).alias("k"), F.sum("m").alias("m"), F.sum("N").alias("N"), F.sum("values").alias("values"), F.sum(ln_fact(F.col("N"))).alias("parts"), F.sum(ln_gamma_step(F.col("m"), F.col("N"))).alias("step")).collect()
            none = {"k": 0, "m": 0, "N": 0, "values": 0.0, "parts": 0.0, "step": 0.0}
            self._sums = {d: none for d in sets} | {gid[r["gid"]]: r.asDict() for r in rows}
        return self._sums

    def shape(self) -> Shape:
        x = self.sums()
        return Shape(int(x["S"]["m"]), int(x["E"]["m"]), int(x["S"]["N"]), int(x["S"]["k"]), int(x["T"]["m"]), int(x["E"]["k"]))


def of_columns(laid: DataFrame, prior: str = "at_most", cuts: list | None = None) -> Grid:
    """Grid of points that carry their parts: (s, t, e, n, s_part, t_part, e_part)."""
    return of_profile(profile(laid), laid, prior, cuts)


def of_profile(base: DataFrame, laid: DataFrame, prior: str = "at_most", cuts: list | None = None) -> Grid:
    """Grid of a profile (as profile() gives it) of laid points."""
    cells = base.groupBy("s_part", "t_part", "e_part").agg(F.sum("n").cast("long").alias("n"))
    values = lambda v, p: base.groupBy(v, p).agg(F.sum("n").cast("long").alias("n")).select(F.col(v).alias("value"), F.col(p).alias("part"), "n")
    t = base.groupBy("t_part").agg(F.sum("n").cast("long").alias("n"), F.min("t_lo").alias("t_lo"), F.max("t_hi").alias("t_hi"))
    return Grid(laid, cells, values("s", "s_part"), values("e", "e_part"), t, prior, cuts, base)


def profile(laid: DataFrame) -> DataFrame:
    """Points by sequence, interval and event: time is folded away once, and all of a grid's tables share this one exchange."""
    return laid.groupBy("s", "s_part", "t_part", "e", "e_part").agg(F.sum("n").cast("long").alias("n"), F.min("t").alias("t_lo"), F.max("t").alias("t_hi"))


def lay(points: DataFrame, s_part: Column, t_part: Column, e_part: Column, prior: str = "at_most") -> Grid:
    """Partitions given by expressions over s, t and e."""
    return of_columns(points.select("s", "t", "e", "n", s_part.cast("int").alias("s_part"), t_part.cast("int").alias("t_part"), e_part.cast("int").alias("e_part")), prior)


def apply(points: DataFrame, s_map: DataFrame, cuts: Sequence, e_map: DataFrame, prior: str = "at_most") -> Grid:
    """Partitions given by maps (value, part) and sorted cuts. Spark broadcasts a map below its threshold and merges larger ones."""
    cuts = list(cuts)
    t_part = interval_of(F.col("t"), cuts) if len(cuts) <= 32 else lookup_interval(F.col("t"), cuts)
    laid = points.withColumn("t_part", t_part)
    # fold time away from the points first: what joins the maps is no longer than the folded table
    s = s_map.select(F.col("value").alias("s"), F.col("part").cast("int").alias("s_part"))
    e = e_map.select(F.col("value").alias("e"), F.col("part").cast("int").alias("e_part"))
    return of_columns(laid.join(s, "s").join(e, "e").select("s", "t", "e", "n", "s_part", "t_part", "e_part"), prior, cuts)


def null(points: DataFrame, prior: str = "at_most") -> Grid:
    one = F.lit(0)
    return lay(points, one, one, one, prior)


def finest(points: DataFrame, prior: str = "at_most") -> Grid:
    """Every distinct value alone; time parts get dense ordered ids."""
    from seqgrid.functions.encode import ordered_ids

    number = lambda v, p: ordered_ids(points.select(v).distinct(), v, name=p)
    laid = points.join(number("s", "s_part"), "s").join(number("t", "t_part"), "t").join(number("e", "e_part"), "e")
    return of_columns(laid.select("s", "t", "e", "n", *[F.col(c).cast("int").alias(c) for c in ("s_part", "t_part", "e_part")]), prior)


__all__ = ["DIMS", "MAX_LITERAL_CUTS", "VALUE", "Grid", "Shape", "apply", "finest", "lay", "null", "of_columns", "of_profile", "profile"]
