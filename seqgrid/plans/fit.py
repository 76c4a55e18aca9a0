"""The parameter-free fit: starts in parallel tasks, the best one kept; distributed merging where the grid outgrows a task."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from seqgrid.functions.encode import interval_of, lookup_interval, ordered_ids, quantile_cuts
from seqgrid.operators import grid, merge, refine, score
from seqgrid.operators.grid import Grid, Shape
from seqgrid.operators.score import cost
from seqgrid.plans import kernel
from seqgrid.sources.persist import cut

KERNEL_POINTS = 8_000_000  # folded points that one task holds (16 bytes each, and the kernel's arrays)
PACK = 1 << 16  # points of a packed block
CAP = 1024  # parts on an axis of a distributed start, at most


def _code(x: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    values, code = np.unique(x.to_numpy(), return_inverse=True)
    return values, code


def data_of(pdf: pd.DataFrame, prior: str) -> tuple[kernel.Data, np.ndarray, np.ndarray, np.ndarray]:
    sv, s = _code(pdf["s"])
    tv, t = _code(pdf["t"])
    ev, e = _code(pdf["e"])
    return kernel.Data(s, t, e, pdf["n"].to_numpy(), len(sv), len(tv), len(ev), prior=prior), sv, tv, ev


def _packed(points: DataFrame) -> DataFrame:
    """(block): the points as compressed tables of some ten thousand rows, with a dictionary for what is not a number; in the shared folder."""

    def pack(batches):  # noqa: ANN001, ANN202
        held, many = [], 0
        for b in batches:
            held.append(b)
            many += b.num_rows
            if many >= PACK:
                yield block(held)
                held, many = [], 0
        if many:
            yield block(held)

    def block(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(held).combine_chunks()
        columns = [c if pa.types.is_integer(c.type) or pa.types.is_floating(c.type) else c.dictionary_encode() for c in table.columns]
        table = pa.table(columns, table.column_names)
        out = pa.BufferOutputStream()
        with pa.ipc.new_stream(out, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
            w.write_table(table)
        return pa.RecordBatch.from_arrays([pa.array([out.getvalue().to_pybytes()], pa.binary())], ["block"])

    return cut(points.mapInArrow(pack, "block binary"))


def _tables(blocks: list[bytes]):  # noqa: ANN202
    for b in blocks:
        with pa.ipc.open_stream(b) as r:
            yield r.read_all()


def _values_of(c: pa.ChunkedArray) -> np.ndarray:
    """The distinct values of a column, in order."""
    c = c.combine_chunks()
    return np.unique(np.array(c.dictionary.to_pylist(), object) if pa.types.is_dictionary(c.type) else c.to_numpy(zero_copy_only=False))


def _codes_of(c: pa.ChunkedArray, values: np.ndarray) -> np.ndarray:
    """Each row's place among values."""
    c = c.combine_chunks()
    if pa.types.is_dictionary(c.type):
        return np.searchsorted(values, np.array(c.dictionary.to_pylist(), object))[c.indices.to_numpy(zero_copy_only=False)]
    return np.searchsorted(values, c.to_numpy(zero_copy_only=False))


def data_of_blocks(blocks: list[bytes], prior: str, parts: dict[str, np.ndarray] | None = None) -> tuple[kernel.Data, np.ndarray, np.ndarray, np.ndarray]:
    """data_of, from packed blocks: values first, then the codes, so that only codes are held for all points. parts gets the part of every value of s and e, where the blocks have them."""
    values: dict[str, list[np.ndarray]] = {k: [] for k in "ste"}
    many = 0
    for table in _tables(blocks):
        many += table.num_rows
        for k, have in values.items():
            have.append(_values_of(table[k]))
            while len(have) > 1 and len(have[-2]) <= 2 * len(have[-1]):  # lists of growing length, each joined to one of like length
                have[-2:] = [np.unique(np.concatenate(have[-2:]))]
    distinct = {k: np.unique(np.concatenate(have)) for k, have in values.items()}
    values.clear()
    code = {k: np.empty(many, np.int32) for k in "ste"}
    n, lo = np.empty(many, np.int64), 0
    for table in _tables(blocks):
        hi = lo + table.num_rows
        for k in "ste":
            code[k][lo:hi] = _codes_of(table[k], distinct[k])
        n[lo:hi] = table["n"].to_numpy()
        if parts is not None:
            for k in "se":
                parts.setdefault(k, np.zeros(len(distinct[k]), np.int64))[code[k][lo:hi]] = table[f"{k}_part"].to_numpy()
        lo = hi
    blocks.clear()
    sv, tv, ev = (distinct[k] for k in "ste")
    return kernel.Data(code.pop("s"), code.pop("t"), code.pop("e"), n, len(sv), len(tv), len(ev), prior=prior), sv, tv, ev


def _types(points: DataFrame) -> dict[str, str]:
    return {f.name: f.dataType.simpleString() for f in points.schema.fields}


def rounds_schema(points: DataFrame) -> str:
    t = _types(points)
    return f"round int, cost double, k_s int, k_t int, k_e int, merges int, evaluations long, moves int, seconds double, s_values array<{t['s']}>, s_parts array<int>, e_values array<{t['e']}>, e_parts array<int>, cuts array<{t['t']}>"


def run_rounds(points: DataFrame, rounds: int = 10, seed: int = 0, start: str = "coarse", pre: bool = True, post: bool = True, prior: str = "at_most", cap: int | None = None, warm: tuple | None = None, shares: list[float] | None = None) -> DataFrame:
    """One row for each start, each computed in a task of its own from the folded points.

    The points are packed once; every task reads all blocks anew, so none are exchanged or sorted for the starts.
    """

    def task(batches):  # noqa: ANN001, ANN202
        held: dict[int, list[bytes]] = {}
        for b in batches:
            for number, block in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                held.setdefault(number, []).append(block)
        for number in list(held):
            yield pa.RecordBatch.from_pandas(start_of(number, held.pop(number)), schema=out, preserve_index=False)

    def start_of(number: int, blocks: list[bytes]) -> pd.DataFrame:
        began = time.time()
        d, sv, tv, ev = data_of_blocks(blocks, prior)
        if warm is None:
            r = kernel.one_round(d, number, seed, start, pre, post, cap)
        else:
            s, e, cuts = warm
            p = kernel.Parts(np.array([s[str(x)] for x in sv]), np.searchsorted(np.array(cuts), tv, side="left") if cuts else np.zeros(len(tv), np.int64), np.array([e[str(x)] for x in ev]))
            rng = np.random.default_rng([seed, number])
            r = kernel.descend(d, kernel.perturb(d, p, rng, shares[number % len(shares)]), rng)
        p = r.parts
        ends = np.flatnonzero(np.diff(p.t))
        k = [int(x.max()) + 1 for x in (p.s, p.t, p.e)]
        return pd.DataFrame({"round": [number], "cost": [r.cost], "k_s": [k[0]], "k_t": [k[1]], "k_e": [k[2]], "merges": [r.merges], "evaluations": [r.evaluations], "moves": [r.moves], "seconds": [time.time() - began], "s_values": [sv.tolist()], "s_parts": [p.s.tolist()], "e_values": [ev.tolist()], "e_parts": [p.e.tolist()], "cuts": [tv[ends].tolist()]})

    schema = rounds_schema(points)
    out = to_arrow_schema(points.sparkSession.createDataFrame([], schema).schema)
    spark = points.sparkSession
    numbers = spark.range(0, rounds, 1, max(rounds, 1)).select(F.col("id").cast("int").alias("round"))
    return numbers.hint("shuffle_replicate_nl").crossJoin(_packed(points.select(*"sten")).coalesce(1)).mapInArrow(task, schema)


def _grid_of(points: DataFrame, row, prior: str) -> Grid:  # noqa: ANN001
    t = _types(points)
    spark = points.sparkSession
    s = spark.createDataFrame(list(zip(row["s_values"], row["s_parts"])), f"value {t['s']}, part int")
    e = spark.createDataFrame(list(zip(row["e_values"], row["e_parts"])), f"value {t['e']}, part int")
    return grid.apply(points, s, row["cuts"], e, prior)


def restarts(points: DataFrame, rounds: int = 10, seed: int = 0, max_seconds: float | None = None, **options) -> tuple[DataFrame, Grid]:  # noqa: ANN003
    """(round, cost, parts, best_so_far) and the best grid. With max_seconds rounds run in waves, and no wave starts after that time: any time it stops, the best so far stands."""
    spark = points.sparkSession
    prior = options.get("prior", "at_most")
    began, rows, done = time.time(), [], 0
    wave = rounds if max_seconds is None else max(1, spark.sparkContext.defaultParallelism)
    while done < rounds and (not rows or time.time() - began < (max_seconds or 1e18)):
        k = min(wave, rounds - done)
        got = run_rounds(points, k, seed + done, **options).collect()
        rows += [r.asDict() | {"round": r["round"] + done} for r in got]
        done += k
    if not rows:
        raise ValueError("no points to fit")
    rows.sort(key=lambda r: r["round"])
    keep = ("round", "cost", "k_s", "k_t", "k_e", "merges", "evaluations", "moves", "seconds")
    log = spark.createDataFrame([tuple(r[c] for c in keep) for r in rows], "round int, cost double, k_s int, k_t int, k_e int, merges int, evaluations long, moves int, seconds double")
    log = log.withColumn("best_so_far", F.min("cost").over(Window.partitionBy(F.lit(0)).orderBy("round").rowsBetween(Window.unboundedPreceding, 0)))
    best = min(rows, key=lambda r: (r["cost"], r["round"]))
    return log, _grid_of(points, best, prior)


def neighbourhood(points: DataFrame, start: Grid, rounds: int = 8, shares: tuple[float, ...] = (0.05, 0.1, 0.2, 0.4), seed: int = 1) -> tuple[DataFrame, Grid]:
    """From an incumbent: perturb it by widening shares, descend again, go back to the narrowest share on success."""
    spark, now, log, g, wide = points.sparkSession, cost(start), [], start, 0
    for wave in range(-(-rounds // len(shares))):
        warm = ({str(r["value"]): r["part"] for r in g.s_values.collect()}, {str(r["value"]): r["part"] for r in g.e_values.collect()}, [r["t_hi"] for r in g.t_parts.orderBy("t_part").collect()][:-1])
        got = run_rounds(points, len(shares), seed + 100 * wave, prior=g.prior, warm=warm, shares=[x * (1 + wide) for x in shares]).collect()
        best = min(got, key=lambda r: (r["cost"], r["round"]))
        log.append((wave, float(best["cost"]), float(min(now, best["cost"]))))
        if best["cost"] < now - kernel.EPS:
            now, g, wide = best["cost"], _grid_of(points, best, g.prior), 0
        else:
            wide += 1
    return spark.createDataFrame(log, "wave int, cost double, best_so_far double"), g


def greedy(points: DataFrame, start: str = "coarse", objective: str = "cost", prior: str = "at_most", reference: bool = False) -> DataFrame:
    """(step, dim, left, right, delta): the path of best merges from a start grid, in one task; reference rescoring every candidate is for tiny data."""

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        d, *_ = data_of(pdf, prior)
        p = kernel.coarse(d) if start == "coarse" else kernel.Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne))
        path = kernel.greedy_reference(d, p)[1] if reference else kernel.greedy(d, p, objective)[1]
        return pd.DataFrame([(i, "STE"[dim], left, right, delta) for i, (dim, left, right, delta) in enumerate(path)], columns=["step", "dim", "left", "right", "delta"])

    return points.groupBy(F.lit(0).alias("all")).applyInPandas(task, "step int, dim string, left int, right int, delta double")


def _alike(points: DataFrame, column: str, cap: int, cuts: list) -> DataFrame:
    """(value, part): at most cap groups of about equal size of values with like profiles over the other coordinates.

    A value's place is the mean of a hash-drawn number for each (interval, other value) that it meets; sorted by place,
    values are dealt to groups in runs.
    """
    other = "e" if column == "s" else "s"
    drawn = F.xxhash64(lookup_interval(F.col("t"), cuts), other) / float(1 << 63)
    place = points.groupBy(F.col(column).alias("value")).agg((F.sum(F.col("n") * drawn) / F.sum("n")).alias("place"))
    # ties by value; the sort key is one column for the range partitions
    ids = ordered_ids(place.select("value", F.struct("place", "value").alias("key")), "key")
    many = max(1, ids.agg(F.max("id")).first()[0] or 0) + 1
    return ids.select("value", F.floor(F.col("id") * cap / F.lit(many)).cast("int").alias("part"))


def coarse_grid(points: DataFrame, cap: int = CAP, prior: str = "at_most") -> Grid:
    """Distributed coarse start: quantile cuts; values alone or, above the cap, groups of values with like profiles."""
    h = points.agg(F.approx_count_distinct("s").alias("n"), F.approx_count_distinct("e").alias("a"), F.sum("n").alias("N")).first()
    cap = min(cap, int((h["N"] or 1) ** 0.5) + 1)
    cuts = quantile_cuts(points, min(cap, max(8, int(h["N"] or 1) // max(1, min(h["n"], cap) * min(h["a"], cap)))))
    few = cuts[:: max(1, len(cuts) // 8)]

    def part(v: str, k: int) -> DataFrame:
        if k > cap:
            return _alike(points, v, cap, few)
        return ordered_ids(points.select(v).distinct(), v).select(F.col(v).alias("value"), F.col("id").cast("int").alias("part"))

    return grid.apply(points, part("s", h["n"]), cuts, part("e", h["a"]), prior)


@dataclass
class _Rolled:
    """Cells of a grid with the sizes of its parts on the driver (at most CAP an axis): all that merging needs."""

    cells: DataFrame
    sizes: dict[str, dict[int, tuple[int, int]]]
    h: Shape
    prior: str

    def parts(self, dim: str) -> DataFrame:
        rows = [(p, int(n), int(m)) for p, (n, m) in sorted(self.sizes[dim].items())]
        return self.cells.sparkSession.createDataFrame(rows, "part int, n_points long, n_values long")

    def shape(self) -> Shape:
        return Shape(self.h.n, self.h.a, self.h.N, *[len(self.sizes[d]) for d in "STE"])

    def merged(self, dim: str, to: dict[int, int]) -> _Rolled:
        """Parts renamed by to, which covers all parts of the axis."""
        size: dict[int, tuple[int, int]] = {}
        for p, (n, m) in self.sizes[dim].items():
            a, b = size.get(to[p], (0, 0))
            size[to[p]] = (a + n, 1 if dim == "T" else b + m)
        c = grid.DIMS[dim]
        names = self.cells.sparkSession.createDataFrame(list(to.items()), f"{c} int, _to int")
        cells = self.cells.join(F.broadcast(names), c).withColumn(c, F.col("_to")).groupBy("s_part", "t_part", "e_part").agg(F.sum("n").cast("long").alias("n"))
        return _Rolled(cut(cells), {**self.sizes, dim: size}, self.h, self.prior)


def greedy_batched(g: Grid, min_gain: float = 0.0, until_cells: int | None = None) -> tuple[Grid, list[tuple]]:
    """Rounds of many merges at once, for grids too large for a task, until no axis has a merge that lowers the cost (or, with until_cells, a task can hold the cells).

    In a round one axis merges its mutually best, disjoint pairs. Their changes add up exactly but for the variable
    level, which is known for any number of merges; the longest prefix by change that lowers the cost is done. Only
    cells take part in the rounds, each round's cells going to the shared folder; the points are labelled once, at the end.
    """
    sizes = {d: {r["part"]: (r["n_points"], r["n_values"]) for r in g.parts(d).collect()} for d in "STE"}
    now = _Rolled(cut(g.cells), sizes, g.shape(), g.prior)
    label = {d: {p: p for p in sizes[d]} for d in "STE"}
    log: list[tuple] = []
    idle = 0
    while idle < 3 and not (until_cells is not None and now.shape().k <= kernel.CELLS and now.cells.count() <= until_cells):
        dim = "STE"[len(log) % 3]
        k = len(now.sizes[dim])
        if k < 2:
            log.append((len(log), dim, 0, 0.0))
            idle += 1
            continue
        step = merge.variable_step(now, dim)
        d = merge.deltas(now, dim).withColumn("own", F.col("delta") - step)
        two = d.select("left", "right", "own", F.explode(F.array("left", "right")).alias("p"))
        first = two.withColumn("r", F.row_number().over(Window.partitionBy("p").orderBy("own", "left", "right"))).where("r = 1")
        mutual = first.groupBy("left", "right", "own").count().where("count = 2").orderBy("own", "left")
        picks = [(r["left"], r["right"], r["own"]) for r in mutual.collect()]  # fewer than the parts of one axis
        run, best, take = 0.0, -min_gain - kernel.EPS, 0
        for m, (_, _, own) in enumerate(picks, 1):
            run += own
            value = run + merge.variable_step(now, dim, m)
            if value < best:
                best, take = value, m
        log.append((len(log), dim, take, best if take else 0.0))
        if not take:
            idle += 1
            continue
        idle = 0
        into = {b: a for a, b, _ in picks[:take]}
        kept = {p: i for i, p in enumerate(sorted(p for p in now.sizes[dim] if p not in into))}
        to = {p: kept[into.get(p, p)] for p in now.sizes[dim]}
        now = now.merged(dim, to)
        label[dim] = {p: to[q] for p, q in label[dim].items()}
    return merge.apply(g, {d: {p: q for p, q in m.items() if p != q} for d, m in label.items()}), log


def _rest(g: Grid) -> Grid:
    """A grid whose labelled points lie in the shared folder."""
    return grid.of_columns(cut(g.laid), g.prior, g.cuts)


def merge_cells(g: Grid, max_cells: int = KERNEL_POINTS, rounds: int = 1, seed: int = 0) -> Grid:
    """Merges of a grid's parts to the optimum: distributed rounds while a task can't hold the cells, then the exact greedy on them in one.

    With rounds > 1 further tasks search from random groupings of the parts. The parts are atoms here, with their sizes.
    """
    g, _ = greedy_batched(g, until_cells=max_cells)
    h, prior = g.shape(), g.prior
    sizes = {d: {r["part"]: r["n_values"] for r in g.parts(d).collect()} for d in "SE"}

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        number = int(pdf["round"].iloc[0])
        (sv, si), (tv, ti), (ev, ei) = (np.unique(pdf[c], return_inverse=True) for c in grid.DIMS.values())
        d = kernel.Data(si, ti, ei, pdf["n"].to_numpy(), len(sv), len(tv), len(ev), np.array([sizes["S"][x] for x in sv]), np.array([sizes["E"][x] for x in ev]), h.n, h.a, prior)
        r = kernel.one_round(d, number, seed, "finest")
        part = lambda v, p: json.dumps({int(a): int(b) for a, b in zip(v, p)})
        return pd.DataFrame({"round": [number], "cost": [r.cost], "s": [part(sv, r.parts.s)], "t": [part(tv, r.parts.t)], "e": [part(ev, r.parts.e)]})

    many = g.cells.crossJoin(F.broadcast(g.cells.sparkSession.range(rounds).select(F.col("id").cast("int").alias("round"))))
    best = min(many.groupBy("round").applyInPandas(task, "round int, cost double, s string, t string, e string").collect(), key=lambda r: (r["cost"], r["round"]))
    return merge.apply(g, {d: {int(a): b for a, b in json.loads(best[c]).items()} for d, c in zip("STE", "ste")})


def move_values(g: Grid, dim: str) -> tuple[Grid, int]:
    """Moves of values until none lowers the cost: one after the other, each by its exact change, in a task that holds the profile; refine.move_values where none does."""
    base = cut(grid.profile(g.laid) if g.base is None else g.base)
    g = grid.of_profile(base, g.laid, g.prior, g.cuts)
    if base.count() > KERNEL_POINTS:
        return refine.move_values(g, dim)
    prior, v = g.prior, grid.VALUE[dim]
    schema = f"value {_types(base)[v]}, to int, moves long"
    out = to_arrow_schema(base.sparkSession.createDataFrame([], schema).schema)

    def task(batches):  # noqa: ANN001, ANN202
        blocks = [x for b in batches for x in b.column(0).to_pylist()]
        if not blocks:
            return
        parts: dict[str, np.ndarray] = {}
        d, sv, _, ev = data_of_blocks(blocks, prior, parts)
        p = kernel.Parts(parts["s"], np.arange(d.nt), parts["e"])
        moves, rng = 0, np.random.default_rng(0)
        while m := kernel.improve_values(d, p, 0 if dim == "S" else 2, rng):
            moves += m
        if moves:
            p = p.tidy(d)
            values, to = (sv, p.s) if dim == "S" else (ev, p.e)
            yield pa.RecordBatch.from_pandas(pd.DataFrame({"value": values.tolist(), "to": to, "moves": moves}), schema=out, preserve_index=False)

    to = cut(_packed(base.select("s", F.col("t_part").alias("t"), "e", "n", "s_part", "e_part")).coalesce(1).mapInArrow(task, schema))
    moves = to.agg(F.max("moves")).first()[0] or 0
    if not moves:
        return g, 0
    return grid.of_profile(cut(refine._relabelled(base, dim, to)), cut(refine._relabelled(g.laid, dim, to)), g.prior, g.cuts), int(moves)


def move_bounds(g: Grid) -> tuple[Grid, int]:
    """Shifts and splits of intervals until neither lowers the cost, in a task that holds the points folded by cluster of sequences, time and cluster of events; refine's passes where none does."""
    folded = cut(g.laid.groupBy(F.col("s_part").alias("s"), "t", F.col("e_part").alias("e"), F.col("s_part"), F.col("t_part"), F.col("e_part")).agg(F.sum("n").cast("long").alias("n")))
    if folded.count() > KERNEL_POINTS:
        g, shifts = refine.move_bounds(g)
        g, splits = refine.split_intervals(_rest(g) if shifts else g)
        return g, shifts + splits
    h, prior = g.shape(), g.prior
    cuts = [r["t_hi"] for r in g.t_parts.orderBy("t_part").collect()][:-1]
    schema = f"cuts array<{_types(folded)['t']}>, moves long"
    out = to_arrow_schema(folded.sparkSession.createDataFrame([], schema).schema)

    def task(batches):  # noqa: ANN001, ANN202
        blocks = [x for b in batches for x in b.column(0).to_pylist()]
        if not blocks:
            return
        d, _, tv, _ = data_of_blocks(blocks, prior)
        d.n_values, d.a_values = h.n, h.a  # a cluster stands for its values
        last = np.zeros(len(tv) + 1, np.int64)
        last[np.searchsorted(tv, np.array(cuts, tv.dtype), side="right")] = 1
        p = kernel.Parts(np.arange(d.ns), np.cumsum(last[:-1]), np.arange(d.ne))
        moves = 0
        while m := kernel.improve_bounds(d, p) + kernel.split_bounds(d, p):
            moves += m
        yield pa.RecordBatch.from_pandas(pd.DataFrame({"cuts": [tv[np.flatnonzero(np.diff(p.t))].tolist()], "moves": [moves]}), schema=out, preserve_index=False)

    got = _packed(folded.select("s", "t", "e", "n")).coalesce(1).mapInArrow(task, schema).first()
    return (_rest(refine._labelled(g, got["cuts"])), int(got["moves"])) if got and got["moves"] else (g, 0)


def improve(g: Grid) -> tuple[Grid, int]:
    """Moves of values and of bounds in turn until none lowers the cost: (grid, moves). The cost falls with every move, so it ends."""
    moved = quiet = turn = 0
    steps = (lambda x: move_values(x, "S"), lambda x: move_values(x, "E"), move_bounds)
    while quiet < len(steps):
        g, m = steps[turn % len(steps)](g)
        turn, moved, quiet = turn + 1, moved + m, 0 if m else quiet + 1
    return g, moved


def fit_distributed(points: DataFrame, rounds: int = 10, seed: int = 0, prior: str = "at_most", post: bool = True) -> Grid:
    """The fit for points that no task holds: merges on cells and moves on all points in turn, until neither lowers the cost; the null grid where that is not worse."""
    points = cut(points)
    g = merge_cells(_rest(coarse_grid(points, prior=prior)), rounds=rounds, seed=seed)
    while post:
        g, moved = improve(g)
        if not moved:
            break
        merged = merge_cells(g)
        if cost(merged) >= cost(g) - kernel.EPS:
            break
        g = _rest(merged)
    return grid.null(points, prior) if score.null_cost(points) <= cost(g) + kernel.EPS else g


def fit(points: DataFrame, rounds: int = 10, seed: int = 0, start: str = "coarse", pre: bool = True, post: bool = True, prior: str = "at_most", max_kernel_points: int = KERNEL_POINTS) -> Grid:
    """The best grid found; no option needs to be set.

    Up to max_kernel_points folded points every start sees all of them. Above, time is cut coarsely; if a task holds the
    points folded so, it is fitted there, and values and bounds are refined on the full points. Else fit_distributed.
    """
    n = points.count()
    if n <= max_kernel_points:
        return restarts(points, rounds, seed, start=start, pre=pre, post=post, prior=prior)[1]
    cuts = quantile_cuts(points, CAP)
    part = interval_of(F.col("t"), cuts) if len(cuts) <= 32 else lookup_interval(F.col("t"), cuts)
    folded = points.groupBy("s", part.alias("i"), "e").agg(F.sum("n").cast("long").alias("n"), F.max("t").alias("hi"))
    if folded.count() > max_kernel_points:
        return fit_distributed(points, rounds, seed, prior, post)
    top = folded.groupBy("i").agg(F.max("hi").alias("t"))
    _, small = restarts(folded.drop("hi").join(F.broadcast(top), "i").select("s", "t", "e", "n"), rounds, seed, start=start, pre=pre, post=post, prior=prior)
    bounds = [r["t_hi"] for r in small.t_parts.orderBy("t_part").collect()][:-1]
    full = grid.apply(points, small.s_values.select("value", "part"), bounds, small.e_values.select("value", "part"), prior)
    return improve(_rest(full))[0] if post else full
