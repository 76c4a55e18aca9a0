"""The search on one grid in memory: merging with stored changes, moves of values and of bounds.

It runs inside one executor task for each start, on counts: folded points (s, t, e, n) coded by dense numbers, t in
order, in 16 bytes each; passes over all points go in blocks of BLOCK. All changes come from the three additive levels of the cost; a merge updates only what it touched.
"""

from __future__ import annotations

import bisect
import heapq
import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

from seqgrid.functions.mathx import lf, lg, ln_partitions

EPS = 1e-9
TIE = 1e-10  # changes this close are equal: sums in another order differ so much
TABLE = 1 << 22
BLOCK = 1 << 20  # points or pairs whose terms are held at once
_table = np.zeros(1)


def lf_of(x: np.ndarray) -> np.ndarray:
    """ln x! of whole numbers."""
    global _table
    x = np.asarray(x)
    top = int(x.max(initial=0))
    if top < TABLE:
        if top >= len(_table):
            size = min(TABLE, max(1 << 12, 2 * top))
            _table = np.concatenate([[0.0], np.cumsum(np.log(np.arange(1, size, dtype=np.float64)))])
        return _table[x.astype(np.int64, copy=False)]
    v = np.maximum(x.astype(np.float64), 18)
    big = (v + 0.5) * np.log(v) - v + 0.5 * math.log(2 * math.pi) + 1 / (12 * v) - 1 / (360 * v**3)
    return np.where(x < 18, lf_of(np.minimum(x, 17)), big)


def _table_to(top: int):  # noqa: ANN202
    """lf_of for numbers up to top: a plain look-up where the table reaches so far."""
    if top >= TABLE:
        return lf_of
    lf_of(np.array([top]))
    return _table.take


def g_of(points: np.ndarray, values: np.ndarray) -> np.ndarray:
    """The part-level cost of a cluster: ln Gamma(N + m) - ln Gamma(m); 0 for no cluster."""
    m = np.maximum(values, 1)
    return np.where(values > 0, lf_of(points + m - 1) - lf_of(m - 1), 0.0)


def _least_type(top: int) -> type:
    return np.int32 if top < 1 << 31 else np.int64


def _blocks(many: int) -> Iterator[slice]:
    for lo in range(0, many, BLOCK):
        yield slice(lo, min(lo + BLOCK, many))


@dataclass
class Data:
    s: np.ndarray
    t: np.ndarray  # sorted
    e: np.ndarray
    n: np.ndarray
    ns: int
    nt: int
    ne: int
    ws: np.ndarray | None = None  # values behind each s, where s itself is a group of them; 1 if not given
    we: np.ndarray | None = None
    n_values: int = 0  # sequences and events in all, for the prior
    a_values: int = 0
    prior: str = "at_most"
    N: int = field(init=False)

    def __post_init__(self) -> None:
        order = np.argsort(self.t, kind="stable")
        order = order.astype(_least_type(len(order)))
        for name, top in (("s", self.ns), ("t", self.nt), ("e", self.ne), ("n", int(np.max(self.n, initial=0)))):
            setattr(self, name, np.asarray(getattr(self, name)).astype(_least_type(top), copy=False)[order])
        self.N = int(self.n.sum(dtype=np.int64))
        self._by: dict[int, np.ndarray] = {}
        self.ws = np.ones(self.ns, np.int64) if self.ws is None else np.asarray(self.ws, np.int64)
        self.we = np.ones(self.ne, np.int64) if self.we is None else np.asarray(self.we, np.int64)
        self.n_values, self.a_values = self.n_values or int(self.ws.sum()), self.a_values or int(self.we.sum())
        self._lb: dict[tuple[int, int], list[float]] = {}

    def by(self, dim: int) -> np.ndarray:
        """The points in the order of their s (0) or e (2)."""
        if dim not in self._by:
            self._by[dim] = np.argsort(self.e if dim else self.s, kind="stable").astype(_least_type(len(self.s)))
        return self._by[dim]

    def ln_b(self, count: int, k: int) -> float:
        """A table for each variable, long enough for all numbers of clusters that occur."""
        have = self._lb.get((count, 0))
        if have is None or len(have) < k:
            have = ln_partitions(count, min(count, max(k, 64)), self.prior)
            self._lb[(count, 0)] = have
        return have[k - 1]

    def variable(self, ks: int, kt: int, ke: int) -> float:
        k = float(ks) * kt * ke
        return self.ln_b(self.n_values, ks) + self.ln_b(self.a_values, ke) + lg(self.N + k) - lg(k) - lf(self.N)

    def constant(self) -> float:
        """What no grid changes; values that stand for groups bring their inner terms from outside."""
        one = lambda x, k: lf_of(np.bincount(x, self.n, k).astype(np.int64)).sum()
        return math.log(self.n_values) + math.log(self.a_values) + math.log(self.N) + lf(self.N) - one(self.s, self.ns) - one(self.e, self.ne)


@dataclass
class Parts:
    """Labels of the s values, the e values and the t values (rising)."""

    s: np.ndarray
    t: np.ndarray
    e: np.ndarray

    def tidy(self, d: Data) -> Parts:
        """Labels without gaps, clusters in the order of their least value."""

        def dense(x: np.ndarray) -> np.ndarray:
            u, first, inv = np.unique(x, return_index=True, return_inverse=True)
            rank = np.empty(len(u), np.int64)
            rank[np.argsort(first)] = np.arange(len(u))
            return rank[inv]

        return Parts(dense(self.s), dense(self.t), dense(self.e))


def tensor(d: Data, p: Parts) -> np.ndarray:
    ks, kt, ke = (int(x.max()) + 1 for x in (p.s, p.t, p.e))
    out, step = np.zeros(ks * kt * ke, np.int64), max(BLOCK, ks * kt * ke)  # a block makes a table of all cells
    for lo in range(0, len(d.s), step):
        at = slice(lo, lo + step)
        cell = p.s[d.s[at]]
        cell *= kt
        cell += p.t[d.t[at]]
        cell *= ke
        cell += p.e[d.e[at]]
        out += np.bincount(cell, d.n[at], len(out)).astype(np.int64)
    return out.reshape(ks, kt, ke)


def _pairs_of(a: np.ndarray, k: int, b: np.ndarray, most: int) -> np.ndarray:
    """a * k + b, below most, for (labels, points) a and b."""
    out = np.empty(len(a[1]), _least_type(most))
    for at in _blocks(len(out)):
        out[at] = a[0][a[1][at]] * k + b[0][b[1][at]]
    return out


def total(d: Data, p: Parts) -> float:
    p = p.tidy(d)
    x = tensor(d, p)
    ms, me = (np.bincount(q, w).astype(np.int64) for q, w in ((p.s, d.ws), (p.e, d.we)))
    part = g_of(x.sum((1, 2)), ms).sum() + g_of(x.sum((0, 1)), me).sum() + lf_of(x.sum((0, 2))).sum()
    return d.constant() + d.variable(*x.shape) + part - lf_of(x).sum()


def null_parts(d: Data) -> Parts:
    z = lambda k: np.zeros(k, np.int64)
    return Parts(z(d.ns), z(d.nt), z(d.ne))


def _pair_sums(a: np.ndarray, w: np.ndarray | None = None) -> np.ndarray:
    """Over the columns of a, each counted w times: sum of lf(x_i + x_j) - lf(x_i) - lf(x_j), for all rows i, j. The diagonal leaves out columns of one row."""
    k, m = a.shape
    out = np.zeros((k, k))
    some = np.flatnonzero((a > 0).sum(0) > 1)
    a = a[:, some]
    w = np.ones(len(some)) if w is None else w[some].astype(np.float64)
    dense = np.count_nonzero(a) > 0.3 * a.size
    if dense or k <= 24:
        step = max(1, (1 << 21) // max(k * k, 1))
        rows = max(1, (1 << 21) // max(k * step, 1))
        for lo in range(0, a.shape[1], step):
            b = np.ascontiguousarray(a[:, lo : lo + step])
            for i in range(0, k, rows):  # pairs of a row and itself or a later one, when they are more than one block
                out[i : i + rows, i:] += lf_of(b[i : i + rows, None, :] + b[None, i:, :]) @ w[lo : lo + step]
        if rows < k:
            for i in range(0, k, rows):
                out[i + rows :, i : i + rows] = out[i : i + rows, i + rows :].T
        r = lf_of(a) @ w
        return out - r[:, None] - r[None, :]
    for c, times in zip(a.T, w.tolist()):
        i = np.flatnonzero(c)
        x = c[i]
        r = lf_of(x)
        out[np.ix_(i, i)] += (lf_of(x[:, None] + x[None, :]) - r[:, None] - r[None, :]) * times
    return out


def _row_sums(a: np.ndarray, i: int, w: np.ndarray | None = None) -> np.ndarray:
    """Row i of _pair_sums."""
    nz = np.flatnonzero(a[i])
    b, x = a[:, nz], a[i, nz]
    w = np.ones(len(nz)) if w is None else w[nz]
    return (lf_of(b + x) - lf_of(b)) @ w - lf_of(x) @ w


def _alike_rows(a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first, kind): the first row of each kind of equal rows, in the order of these, and every row's kind."""
    code = a @ np.random.default_rng(5).integers(1, 1 << 62, a.shape[1])  # wraps; equal rows have equal codes
    _, first, kind = np.unique(code, return_index=True, return_inverse=True)
    if any((a[lo : lo + 4096] != a[first[kind[lo : lo + 4096]]]).any() for lo in range(0, len(a), 4096)):
        _, first, kind = np.unique(a, axis=0, return_index=True, return_inverse=True)
    rank = np.empty(len(first), np.int64)
    rank[np.argsort(first)] = np.arange(len(first))
    return np.sort(first), rank[kind.reshape(-1)]


class Merger:
    """Greedy merging. After each merge only the pairs that it touched are evaluated again.

    Sequence clusters with equal cells and equally many members are one kind: x, size, members and value hold a row for
    each kind, and count says how many clusters it stands for. So the pairs of a start of single sequences are those of
    the kinds of sequences, however many there are of each.
    """

    def __init__(self, d: Data, p: Parts, objective: str = "cost"):
        self.d, p = d, p.tidy(d)
        self.p, self.objective = p, objective
        x = tensor(d, p)
        self.k = list(x.shape)
        self.size = [x.sum((1, 2)), x.sum((0, 2)), x.sum((0, 1))]
        self.members = [np.bincount(p.s, d.ws).astype(np.int64), np.ones(x.shape[1], np.int64), np.bincount(p.e, d.we).astype(np.int64)]
        first, self.kind = _alike_rows(np.concatenate([x.reshape(self.k[0], -1), self.members[0][:, None]], 1))
        self.x, self.size[0], self.members[0] = x if len(first) == len(x) else x[first], self.size[0][first], self.members[0][first]
        self.count = np.bincount(self.kind)
        by = np.argsort(self.kind, kind="stable")  # ascending within a kind
        self.slots = [q.tolist() for q in np.split(by, np.cumsum(self.count)[:-1])]
        self.alive = np.ones(self.k[0], bool)
        self.label = [np.arange(k) for k in self.k]
        self.evaluations = self.merges = 0
        self.cell: list[np.ndarray] = [self._kinds(self._flat(0)), self._neighbours(), -_pair_sums(self._flat(2), self._times(2))]
        self.part = [self._part_matrix(0), None, self._part_matrix(2)]
        self.evaluations += sum(k * (k - 1) // 2 for k in (self.k[0], self.k[2])) + self.k[1] - 1
        self.value = [self.cell[0] + self.part[0], self._time_values(), self._both(2)]
        self._no_self()
        self._line()

    def _line(self) -> None:
        """Intervals in a row: the next and the one before; dead ones stay in place until _squeeze."""
        k = self.x.shape[1]
        self.here, self.next, self.prev = np.ones(k, bool), list(range(1, k + 1)), list(range(-1, k - 1))

    def _squeeze(self) -> None:
        """Take dead intervals out of the arrays."""
        if self.k[1] == len(self.here):
            return
        keep = np.flatnonzero(self.here)
        self.label[1] = (np.cumsum(self.here) - 1)[self.label[1]]
        self.x, self.size[1], self.members[1] = self.x[:, keep], self.size[1][keep], self.members[1][keep]
        self.cell[1], self.value[1] = self.cell[1][keep[:-1]], self.value[1][keep[:-1]]
        self._line()

    def _flat(self, dim: int) -> np.ndarray:
        return np.moveaxis(self.x, dim, 0).reshape(self.x.shape[dim], -1)

    def _times(self, dim: int) -> np.ndarray:
        """How often each column of _flat(1) or _flat(2) counts."""
        return np.repeat(self.count, self.x.shape[3 - dim])

    def _kinds(self, a: np.ndarray) -> np.ndarray:
        """Cell terms of merging clusters of two kinds, or two of one kind."""
        out = -_pair_sums(a)
        out[np.diag_indices(len(a))] = (2 * lf_of(a) - lf_of(2 * a)).sum(1)
        return out

    def _no_self(self) -> None:
        """A kind of one cluster has no pair in itself."""
        i = np.flatnonzero(self.count < 2)
        self.value[0][i, i] = np.inf

    def _g(self, dim: int, n: np.ndarray, m: np.ndarray) -> np.ndarray:
        return lf_of(n) if dim == 1 or self.objective == "likelihood" else g_of(n, m)

    def _part_matrix(self, dim: int) -> np.ndarray:
        n, m = self.size[dim], self.members[dim]
        g = self._g(dim, n, m)
        return self._g(dim, n[:, None] + n[None, :], m[:, None] + m[None, :]) - g[:, None] - g[None, :]

    def _both(self, dim: int) -> np.ndarray:
        v = self.cell[dim] + self.part[dim]
        v[np.tril_indices(len(v))] = np.inf
        return v

    def _neighbours(self) -> np.ndarray:
        a, b = self.x[:, :-1], self.x[:, 1:]
        return ((lf_of(a) + lf_of(b) - lf_of(a + b)) * self.count[:, None, None]).sum((0, 2)) if self.x.shape[1] > 1 else np.empty(0)

    def _time_values(self) -> np.ndarray:
        n = self.size[1]
        return self.cell[1] + lf_of(n[:-1] + n[1:]) - lf_of(n[:-1]) - lf_of(n[1:])

    def _step(self, dim: int) -> float:
        if self.objective == "likelihood":
            return 0.0
        k = list(self.k)
        k[dim] -= 1
        return self.d.variable(*k) - self.d.variable(*self.k)

    def best(self) -> tuple[float, int, int, int] | None:
        """(change, dimension, left, right) of the best merge; ties go to S, T, E, then to lower parts."""
        found = []
        for dim in range(3):
            if self.k[dim] < 2:
                continue
            v = self.value[dim]
            if dim == 0:
                low = v.min()
                pairs = ((self.slots[i][0], self.slots[j][0]) if i != j else self.slots[i][:2] for i, j in np.argwhere(v <= low + TIE))
                left, right = min((min(q), max(q)) for q in pairs)
                left, right = int(self.alive[:left].sum()), int(self.alive[:right].sum())
            else:
                i = int(v.argmin())
                low = v.flat[i]
                if dim == 1:
                    left = int(self.here[:i].sum())
                    right = left + 1
                else:
                    left, right = divmod(i, v.shape[1])
            found.append((float(low) + self._step(dim), dim, left, right))
        if not found:
            return None
        least = min(f[0] for f in found)
        return next(f for f in found if f[0] <= least + 1e-12)

    def merge(self, dim: int, a: int, b: int) -> None:
        """Join b into a (a < b)."""
        if dim != 1 or self.k[1] < len(self.here) // 2:
            self._squeeze()
        x = self.x
        if dim == 1 and self.k[1] < len(self.here):
            a = int(np.flatnonzero(self.here)[a])
            b = self.next[a]
        if dim == 0:
            slots = np.flatnonzero(self.alive)[[a, b]].tolist()
            a, b = self.kind[slots].tolist()
        xa, xb = (x[tuple(i if q == dim else slice(None) for q in range(3))] for i in (a, b))  # np.take would copy all of an x that isn't contiguous
        xm = xa + xb
        rest = [k for k in range(3) if k != dim]
        for pos, other in enumerate(rest):
            flat = lambda y: np.moveaxis(y, pos, 0).reshape(y.shape[pos], -1)
            # columns of one cluster of S are single; all others count as often as their kind
            w = None if dim == 0 or other == 0 else self.count
            if other == 1:
                def near(y: np.ndarray) -> np.ndarray:
                    u = flat(y)
                    return (lf_of(u[:-1]) + lf_of(u[1:]) - lf_of(u[:-1] + u[1:])) @ (np.ones(u.shape[1]) if w is None else w)

                if len(self.cell[1]):
                    change = near(xm) - near(xa) - near(xb)
                    self.cell[1] += change
                    self.value[1] += change
            else:
                sums = self._kinds if other == 0 else lambda y: -_pair_sums(y, w)
                change = sums(flat(xm)) - sums(flat(xa)) - sums(flat(xb))
                self.cell[other] += change
                self.value[other] += change
            self.evaluations += self.k[other] - (other == 1)
        self.k[dim] -= 1
        self.merges += 1
        if dim == 0:
            self._join(a, b, *slots, xm)
            return
        if dim == 1:
            x[:, a], x[:, b] = xm, 0
            size, end = self.size[1], len(self.here)
            size[a] += size[b]
            size[b] = 0
            self.here[b] = False
            self.next[a] = after = self.next[b]
            if after < end:
                self.prev[after] = a
            if b < end - 1:
                self.cell[1][b], self.value[1][b] = 0.0, np.inf
            if after == end:
                self.cell[1][a], self.value[1][a] = 0.0, np.inf
            for j in (self.prev[a], a):
                if j >= 0 and (after := self.next[j]) < end:
                    u, v = x[:, j], x[:, after]
                    self.cell[1][j] = ((lf_of(u) + lf_of(v) - lf_of(u + v)) * self.count[:, None]).sum()
                    self.value[1][j] = self.cell[1][j] + lf(int(size[j] + size[after])) - lf(int(size[j])) - lf(int(size[after]))
            return
        x[:, :, a] = xm
        self.x = np.delete(x, b, axis=2)
        for name in (self.size, self.members):
            name[2][a] += name[2][b]
            name[2] = np.delete(name[2], b)
        self.label[2] = np.where(self.label[2] == b, a, np.where(self.label[2] > b, self.label[2] - 1, self.label[2]))
        for name in (self.cell, self.value):
            name[2] = np.delete(np.delete(name[2], b, 0), b, 1)
        row, full = self._row(2, a, self._times(2))
        self.cell[2][a, :] = self.cell[2][:, a] = row
        self.value[2][a, a + 1 :] = full[a + 1 :]
        self.value[2][:a, a] = full[:a]

    def _row(self, dim: int, a: int, w: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Cell terms, and these with the part terms, of merging a with each other part."""
        row = -_row_sums(self._flat(dim), a, w)
        n, m = self.size[dim], self.members[dim]
        return row, row + self._g(dim, n + n[a], m + m[a]) - self._g(dim, n, m) - self._g(dim, n[a : a + 1], m[a : a + 1])

    def _join(self, a: int, b: int, left: int, right: int, xm: np.ndarray) -> None:
        """The clusters left and right, of kinds a and b, become one cluster left: of a kind there is already, or a new one."""
        n, m = int(self.size[0][a] + self.size[0][b]), int(self.members[0][a] + self.members[0][b])
        for kind, slot in ((a, left), (b, right)):
            self.slots[kind].pop(bisect.bisect_left(self.slots[kind], slot))
            self.count[kind] -= 1
        self.alive[right] = False
        self.label[0][self.label[0] == right] = left
        like = [i for i in np.flatnonzero((self.size[0] == n) & (self.members[0] == m) & (self.count > 0)) if (self.x[i] == xm).all()]
        if like:
            c = int(like[0])
        else:
            c = next((i for i in (a, b) if not self.count[i]), len(self.count))
            if c == len(self.count):
                grow = lambda y: np.concatenate([y, y[:1]])
                self.x, self.size[0], self.members[0], self.count = grow(self.x), grow(self.size[0]), grow(self.members[0]), np.append(self.count, 0)
                self.cell[0], self.value[0] = (np.pad(y[0], (0, 1)) for y in (self.cell, self.value))
                self.slots.append([])
            self.x[c], self.size[0][c], self.members[0][c] = xm, n, m
        self.count[c] += 1
        bisect.insort(self.slots[c], left)
        self.kind[left] = c
        if self.count[c] < 3:  # a new row, or its first pair in itself
            row, full = self._row(0, c)
            self.cell[0][c, :] = self.cell[0][:, c] = row
            self.value[0][c, :] = self.value[0][:, c] = full
        gone = np.flatnonzero(self.count == 0)
        if len(gone):
            self.x, self.size[0], self.members[0], self.count = (np.delete(y, gone, 0) for y in (self.x, self.size[0], self.members[0], self.count))
            for name in (self.cell, self.value):
                name[0] = np.delete(np.delete(name[0], gone, 0), gone, 1)
            self.slots = [q for q in self.slots if q]
            self.kind -= np.searchsorted(gone, self.kind)  # dead clusters' kinds mean nothing
        self._no_self()

    def parts(self) -> Parts:
        rank = np.cumsum(self.alive) - 1
        return Parts(rank[self.label[0]][self.p.s], (np.cumsum(self.here) - 1)[self.label[1]][self.p.t], self.label[2][self.p.e])


def greedy(d: Data, p: Parts, objective: str = "cost") -> tuple[Parts, list[tuple], Merger]:
    """Best merges while they lower the cost; the path as (dim, left, right, change)."""
    m, path = Merger(d, p, objective), []
    while (b := m.best()) and b[0] < -EPS:
        m.merge(*b[1:])
        path.append((b[1], b[2], b[3], b[0]))
    return m.parts(), path, m


def greedy_reference(d: Data, p: Parts) -> tuple[Parts, list[tuple]]:
    """The literal greedy: each candidate is scored from scratch. For tiny data."""
    p, path = p.tidy(d), []
    while True:
        now, found = total(d, p), None
        for dim, lab in enumerate((p.s, p.t, p.e)):
            k = int(lab.max()) + 1
            for i in range(k):
                for j in range(i + 1, k) if dim != 1 else range(i + 1, min(i + 2, k)):
                    new = np.where(lab == j, i, np.where(lab > j, lab - 1, lab))
                    q = Parts(*[new if x == dim else y for x, y in enumerate((p.s, p.t, p.e))])
                    delta = total(d, q) - now
                    if found is None or delta < found[0] - 1e-10:
                        found = (delta, dim, i, j, q)
        if found is None or found[0] >= -EPS:
            return p, path
        p = found[4]
        path.append((found[1], found[2], found[3], found[0]))


def merge_to_null(d: Data, p: Parts) -> list[tuple]:
    """All merges down to one cell: (dim, left, right, change, k_s, k_t, k_e after it)."""
    m, out = Merger(d, p), []
    while b := m.best():
        m.merge(*b[1:])
        out.append((b[1], b[2], b[3], b[0], *m.k))
    return out


def _by_value(own: np.ndarray, cell: np.ndarray, n: np.ndarray, values: int, cells: int, order: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, list[int]]:
    """The points of every value folded by cell: cells and weights, value after value, and where each value's stretch begins. order: the points by their own value."""
    order = np.argsort(own, kind="stable") if order is None else order
    end = np.concatenate([[0], np.cumsum(np.bincount(own, minlength=values))])
    got, edge, lo = [], [0], 0
    while lo < values:  # whole values, about a block of points
        hi = max(lo + 1, int(np.searchsorted(end, end[lo] + BLOCK, side="right")) - 1)
        at = order[end[lo] : end[hi]]
        key = (own[at].astype(np.int64) - lo) * cells + cell[at]
        by = np.argsort(key, kind="stable")
        key = key[by]
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        weight = np.add.reduceat(n[at[by]], first, dtype=np.int64) if len(key) else n[:0]
        key = key[first]
        got.append(((key % cells).astype(_least_type(cells)), weight.astype(_least_type(int(weight.max(initial=0))))))
        edge += (edge[-1] + np.searchsorted(key, np.arange(1, hi - lo + 1) * cells)).tolist()
        lo = hi
    return *(np.concatenate(x) for x in zip(*got)), edge


def improve_values(d: Data, p: Parts, dim: int, rng: np.random.Generator, passes: int = 4) -> int:
    """Move single values of S (0) or E (2) to the cluster that lowers the cost most. Changes p; returns the number of moves.

    A value's cells stay the same while the other axes rest, so they are folded once; a move changes two clusters only.
    """
    p.s, p.t, p.e = (lambda q: (q.s, q.t, q.e))(p.tidy(d))
    x = np.moveaxis(tensor(d, p), dim, 0)
    k = x.shape[0]
    x = np.ascontiguousarray(x.reshape(k, -1).T)  # a row for each cell, so that a value's cells are whole rows
    lab, own, w = (p.s, d.s, d.ws) if dim == 0 else (p.e, d.e, d.we)
    kt, ke = int(p.t.max()) + 1, int(p.e.max()) + 1
    cell = _pairs_of((p.t, d.t), ke, (p.e, d.e), len(x)) if dim == 0 else _pairs_of((p.s, d.s), kt, (p.t, d.t), len(x))
    cells, weight, edge = _by_value(own, cell, d.n, len(lab), len(x), d.by(dim))
    del cell
    size, members = x.sum(0), np.bincount(lab, w, k).astype(np.int64)
    shape = [int(q.max()) + 1 for q in (p.s, p.t, p.e)]
    f = _table_to(d.N + int(w.sum()))
    moves = 0
    g, alive = g_of(size, members), int((members > 0).sum())
    more = np.empty(x.shape)  # what one point more adds to ln x! of a cell
    for lo in range(0, len(x), max(1, BLOCK // k)):
        at = slice(lo, lo + max(1, BLOCK // k))
        more[at] = f(x[at] + 1) - f(x[at])
    most = np.maximum.reduceat(weight, np.minimum(edge[:-1], len(weight) - 1)).tolist() if len(weight) else []
    gone = np.where(members > 0, 0.0, np.inf)
    for _ in range(passes):
        before = moves
        for v in rng.permutation(len(lab)).tolist():
            lo, hi = edge[v], edge[v + 1]
            if lo == hi or alive < 2:
                continue
            at, add = cells[lo:hi], weight[lo:hi]
            n, c, mv = int(add.sum()), int(lab[v]), int(w[v])
            m = members + mv
            if most[v] == 1:
                cell_level = -more.take(at, 0).sum(0)
            else:
                have = x.take(at, 0)
                cell_level = (f(have) - f(have + add[:, None])).sum(0)
            delta = cell_level + f(size + m + (n - 1)) - f(m - 1) - g + gone
            delta[c] = np.inf
            to = int(delta.argmin())
            lone = int(members[c]) == mv
            rest = int(members[c]) - mv
            own_cells = x[at, c]
            leave = float((f(own_cells) - f(own_cells - add)).sum()) - float(g[c])
            change = float(delta[to]) + leave
            if lone:
                less = list(shape)
                less[dim] = alive - 1
                now = list(shape)
                now[dim] = alive
                change += d.variable(*less) - d.variable(*now)
            else:
                change += float(f(size[c] - n + rest - 1) - f(rest - 1))
            if change < -EPS:
                x[at, c] -= add
                x[at, to] += add
                for part in (c, to):
                    more[at, part] = f(x[at, part] + 1) - f(x[at, part])
                for part, sign in ((c, -1), (to, 1)):
                    size[part] += sign * n
                    members[part] += sign * mv
                    g[part] = g_of(size[part : part + 1], members[part : part + 1])[0]
                if lone:
                    alive -= 1
                    gone[c] = np.inf
                lab[v] = to
                moves += 1
        if moves == before:
            break
    return moves


def _cut_costs(cell: np.ndarray, n: np.ndarray, t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(stop, cost): the last points of the distinct times of a stretch but the last, and the cost of cutting the stretch behind each, up to a constant."""
    stop = np.flatnonzero(t[1:] != t[:-1])
    if not len(stop):
        return stop, np.zeros(0)
    order = np.argsort(cell, kind="stable").astype(_least_type(len(cell)))
    cs = cell[order]
    first = np.concatenate([[True], cs[1:] != cs[:-1]])
    del cs
    many = int(n.sum(dtype=np.int64))
    run = np.cumsum(n[order], dtype=_least_type(many))
    begin = np.flatnonzero(first)
    base = np.concatenate([[0], run[begin[1:] - 1]]).astype(np.int64)
    size = np.diff(base, append=many)
    step, group = np.empty(len(order)), 0
    for at in _blocks(len(order)):
        own = np.cumsum(first[at]) + (group - 1)
        group = int(own[-1]) + 1
        nn = n[order[at]].astype(np.int64)
        upto, whole = run[at] - base[own], size[own]
        step[order[at]] = lf_of(upto) - lf_of(upto - nn) + lf_of(whole - upto) - lf_of(whole - upto + nn)
    del order, run, first
    gone = np.cumsum(step, out=step)[stop]
    left = np.cumsum(n, dtype=np.int64)[stop]
    return stop, lf_of(left) + lf_of(many - left) - gone


def improve_bounds(d: Data, p: Parts, passes: int = 6) -> int:
    """Shift each bound to the best place between its neighbours, exactly. Changes p; returns the number of shifts."""
    p.s, p.t, p.e = (lambda q: (q.s, q.t, q.e))(p.tidy(d))
    ks, kt, ke = (int(x.max()) + 1 for x in (p.s, p.t, p.e))
    if kt < 2:
        return 0
    cell = _pairs_of((p.s, d.s), ke, (p.e, d.e), ks * ke)
    ends = np.flatnonzero(np.diff(p.t)).tolist()  # last t value of each interval but the last
    first = np.searchsorted(d.t, np.arange(d.nt + 1))
    shifts = 0
    active = set(range(kt - 1))
    for _ in range(passes):
        todo, active = sorted(active), set()
        for j in todo:
            a = ends[j - 1] + 1 if j else 0
            b = ends[j + 1] if j + 2 < kt else d.nt - 1
            lo, hi = first[a], first[b + 1]
            stop, value = _cut_costs(cell[lo:hi], d.n[lo:hi], d.t[lo:hi])
            if not len(stop):
                continue
            i = int(value.argmin())
            now = int(np.searchsorted(stop, first[ends[j] + 1] - lo - 1))
            if value[i] < value[now] - EPS:
                ends[j] = int(d.t[lo + stop[i]])
                shifts += 1
                active |= {k for k in (j - 1, j, j + 1) if 0 <= k < kt - 1}
        if not active:
            break
    mark = np.zeros(d.nt, np.int64)
    mark[np.array(ends, np.int64) + 1] = 1
    p.t = np.cumsum(mark)
    return shifts


def split_bounds(d: Data, p: Parts) -> int:
    """Cut the interval whose best split lowers the cost most, again and again. Changes p; returns the number of splits.

    Merging can't undo a bound that a start never had. A cut changes nothing for the other intervals, so only its two
    sides are looked at again.
    """
    q = p.tidy(d)
    p.s, p.t, p.e = q.s, q.t, q.e
    ks, kt, ke = (int(x.max()) + 1 for x in (p.s, p.t, p.e))

    def best(lo: int, hi: int) -> tuple[float, int, int, int]:
        """(change without the variable level, lo, hi, last point of the left side) of the best cut of the points lo to hi."""
        cell = _pairs_of((p.s, d.s[lo:hi]), ke, (p.e, d.e[lo:hi]), ks * ke)
        stop, value = _cut_costs(cell, d.n[lo:hi], d.t[lo:hi])
        if not len(stop):
            return np.inf, lo, hi, lo
        i = int(value.argmin())
        return float(value[i] - lf(int(d.n[lo:hi].sum(dtype=np.int64)))), lo, hi, lo + int(stop[i])

    edge = np.searchsorted(d.t, np.searchsorted(p.t, np.arange(kt + 1))).tolist()
    found = [best(lo, hi) for lo, hi in zip(edge[:-1], edge[1:])]
    heapq.heapify(found)
    mark, splits = np.zeros(d.nt, np.int64), 0
    while found:
        value, lo, hi, at = found[0]
        if value + d.variable(ks, kt + 1, ke) - d.variable(ks, kt, ke) >= -EPS:
            break
        heapq.heapreplace(found, best(lo, at + 1))
        heapq.heappush(found, best(at + 1, hi))
        mark[d.t[at] + 1] = 1
        kt += 1
        splits += 1
    p.t = p.t + np.cumsum(mark)
    return splits


def alternate(d: Data, p: Parts, rng: np.random.Generator, rounds: int = 3, splits: bool = False) -> int:
    moves = 0
    for _ in range(rounds):
        m = improve_values(d, p, 0, rng) + improve_values(d, p, 2, rng) + improve_bounds(d, p) + (split_bounds(d, p) if splits else 0)
        moves += m
        if not m:
            break
    return moves


CELLS = 24_000_000


def equal_frequency(d: Data, k: int) -> np.ndarray:
    """Labels of the t values in at most k intervals of about equal weight."""
    w = np.bincount(d.t, d.n, d.nt)
    upto = np.cumsum(w) - w / 2
    lab = np.minimum((upto * k / max(d.N, 1)).astype(np.int64), k - 1)
    return np.unique(lab, return_inverse=True)[1]


def _profiles(d: Data, kt: int, dim: int, bins: int, rng: np.random.Generator) -> np.ndarray:
    """Random projections of the values' frequency profiles, for start groups of values that look alike."""
    t = equal_frequency(d, kt)
    many = (int(t.max()) + 1) * (d.ns if dim else d.ne)
    other = _pairs_of((t, d.t), d.ns, (np.arange(d.ns), d.s), many) if dim else _pairs_of((t, d.t), d.ne, (np.arange(d.ne), d.e), many)
    own, k = (d.s, d.ns) if dim == 0 else (d.e, d.ne)
    r = rng.normal(size=(int(other.max()) + 1, bins)).astype(np.float32)
    out = np.stack([np.bincount(own, d.n * r[other, b], k) for b in range(bins)], 1)
    return out / np.maximum(np.bincount(own, d.n, k), 1)[:, None]


def coarse(d: Data, cap: int | None = None) -> Parts:
    """At most sqrt(N) parts on an axis: equal-frequency intervals, values themselves or groups of alike ones."""
    cap = max(2, cap or math.ceil(math.sqrt(d.N)))
    rng = np.random.default_rng(3)

    def values(k: int, dim: int) -> np.ndarray:
        if k <= cap:
            return np.arange(k)
        score = _profiles(d, min(8, cap), dim, 1, rng)[:, 0]
        lab = np.empty(k, np.int64)
        lab[np.argsort(score, kind="stable")] = np.arange(k) * cap // k
        return lab

    s, e = values(d.ns, 0), values(d.ne, 2)
    # with far fewer points than cells no two parts share a cell and merging has nothing to go by
    room = max(8, min(CELLS, d.N) // max(1, (int(s.max()) + 1) * (int(e.max()) + 1)))
    return Parts(s, equal_frequency(d, min(cap, room, d.nt)), e)


def random_start(d: Data, rng: np.random.Generator, cap: int | None = None) -> Parts:
    cap = max(2, cap or math.ceil(math.sqrt(d.N)))
    pick = lambda most: int(min(most, max(2, round(math.exp(rng.uniform(math.log(2), math.log(max(3, most)))))))) if most > 1 else 1
    ks, ke = pick(min(d.ns, cap, 24)), d.ne if d.ne <= 64 else pick(min(d.ne, cap, 64))
    kt = pick(min(d.nt, cap, 96))
    cuts = np.zeros(d.nt, np.int64)
    if d.nt <= 32 and rng.random() < 0.5:
        cuts[1:] = 1
    elif kt > 1:
        w = np.cumsum(np.bincount(d.t, d.n, d.nt))
        at = np.searchsorted(w, rng.uniform(0, d.N, kt - 1))
        cuts[np.clip(at, 1, d.nt - 1)] = 1
    s = rng.integers(0, ks, d.ns)
    return Parts(s, np.cumsum(cuts), np.arange(d.ne) if ke == d.ne else rng.integers(0, ke, d.ne)).tidy(d)


def perturb(d: Data, p: Parts, rng: np.random.Generator, share: float) -> Parts:
    """Split and shuffle a share of the values, and add random bounds: a neighbour of p that grows with the share."""
    q = Parts(p.s.copy(), p.t.copy(), p.e.copy())
    for lab, k in ((q.s, d.ns), (q.e, d.ne)):
        who = rng.random(k) < share
        lab[who] = lab.max() + 1 + rng.integers(0, max(1, int(2 + 6 * share)), who.sum())
    extra = np.zeros(d.nt, np.int64)
    if d.nt > 1:
        extra[rng.integers(1, d.nt, max(1, int(share * 16)))] = 1
    q.t = np.cumsum(np.concatenate([[0], (np.diff(q.t) > 0).astype(np.int64)]) | extra)
    return q.tidy(d)


@dataclass
class Result:
    parts: Parts
    cost: float
    merges: int
    evaluations: int
    moves: int


def descend(d: Data, p: Parts, rng: np.random.Generator, pre: bool = True, post: bool = True) -> Result:
    """Improve, merge, improve, until neither merging nor moving helps; the null grid where it is not worse."""
    merges = evaluations = moves = 0
    if pre:
        moves += alternate(d, p, rng, 2)
    for _ in range(4):
        p, path, m = greedy(d, p)
        merges, evaluations = merges + m.merges, evaluations + m.evaluations
        moved = alternate(d, p, rng, splits=True) if post else 0
        moves += moved
        if not moved:
            break
    p = p.tidy(d)
    cost, null = total(d, p), null_parts(d)
    empty = total(d, null)
    if empty <= cost + EPS:
        p, cost = null, empty
    return Result(p, cost, merges, evaluations, moves)


def one_round(d: Data, number: int, seed: int, start: str = "coarse", pre: bool = True, post: bool = True, cap: int | None = None) -> Result:
    """Round 0 begins with the coarse (or finest) grid, the others with random ones."""
    rng = np.random.default_rng([seed, number])
    if number == 0:
        p = coarse(d, cap) if start == "coarse" else Parts(np.arange(d.ns), np.arange(d.nt), np.arange(d.ne))
        # a start of single values is no optimum of moves; with few points for each it would only wander
        return descend(d, p, rng, pre and start == "coarse" and (int(p.s.max()) + 1 < d.ns), post)
    return descend(d, random_start(d, rng, cap), rng, pre, post)


__all__ = ["Data", "Merger", "Parts", "Result", "coarse", "descend", "greedy", "greedy_reference", "improve_bounds", "improve_values", "merge_to_null", "null_parts", "one_round", "perturb", "random_start", "tensor", "total"]
