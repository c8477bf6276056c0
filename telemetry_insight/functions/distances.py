"""Summed Euclidean distances of places in the plane to all places of each rank, without making all pairs.

The plane is cut into square cells, again where a cell or one beside it holds more than `most` places. Places of
neighbouring cells are compared one by one. Cells that do not touch act on each other through NODES x NODES
Chebyshev nodes of each (the fast multipole method on interpolation): the distance is smooth there, and what the
nodes leave out is at most a few parts in 1e11 of a pair's distance, below what six digits of a mean show.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Nodes of a cell along each axis.
NODES = 16
#: Levels of cells counted by one aggregate, and most levels. Cells of the last are compared whole.
STEP, LEVELS = 3, 48
#: Rows and columns of the tiles of places whose distances are held at once.
TILE = (128, 1024)

_X = np.cos((np.arange(NODES) + 0.5) * math.pi / NODES)
_C = np.polynomial.chebyshev.chebvander(_X, NODES - 1).T * np.where(np.arange(NODES) == 0, 1.0, 2.0)[:, None] / NODES
#: Nodes of the lower and upper half of a cell, in the polynomials of the whole.
_HALVES = [np.polynomial.chebyshev.chebvander((_X + s) / 2, NODES - 1) @ _C for s in (-1, 1)]
_BESIDE = [(x, y) for x in (-1, 0, 1) for y in (-1, 0, 1)]


def basis(t):
    """The nodes' polynomials at t in [-1, 1], one row a t."""
    return np.polynomial.chebyshev.chebvander(t, NODES - 1) @ _C


def _kernel(dx: int, dy: int):
    """Distances of the nodes of a cell (rows) and of that dx, dy cells on (columns), in half sides of a cell."""
    a, b = _X[:, None] - _X[None, :] - 2 * dx, _X[:, None] - _X[None, :] - 2 * dy
    return np.sqrt(a[:, None, :, None] ** 2 + b[None, :, None, :] ** 2).reshape(NODES**2, NODES**2)


@dataclass
class Level:
    """Cells of a level in order (x, then y): their places, and the charges of the ranks that they hold."""

    x: np.ndarray
    y: np.ndarray
    n: np.ndarray
    leaf: np.ndarray  # number of the leaf, or -1
    first: np.ndarray | None = None  # where a cell's charges start, and their end
    rank: np.ndarray | None = None
    charge: np.ndarray | None = None

    def find(self, x, y):
        """Where cells are, or -1."""
        if not len(self.x):
            return np.full(len(x), -1)
        own = self.x + 1j * self.y  # whole numbers below 2 ** 50: exact, and ordered as (x, y)
        at = np.minimum(np.searchsorted(own, x + 1j * np.asarray(y)), len(own) - 1)
        return np.where((self.x[at] == x) & (self.y[at] == y), at, -1)


class Cells:
    """The cells of a table, and what is near and far of each. Held by the driver and sent to the tasks: as many as places / most, a bounded number."""

    def __init__(self, low, high, most: int, count):
        """low, high: bounds of both axes. count(scale, kept, scale_kept): x, y and number of places of cells of side 1 / scale that are in kept cells (all: None)."""
        self.most = most
        self.exponent = max(-900, math.frexp(max(map(abs, (*low, *high))))[1])  # all coordinates are below 2 ** exponent, so that scaling by powers of two and flooring are exact
        at = lambda level: [math.floor(h * self.scale(level)) - math.floor(v * self.scale(level)) for v, h in zip(low, high, strict=True)]
        self.top = max(level for level in range(LEVELS + 1) if max(at(level)) <= 1)  # its cells touch each other
        self.levels: dict[int, Level] = {}
        x, y, n = count(self.scale(self.top), None, None)
        level = self.top
        self._add(level, x, y, n)
        while (kept := self._split(level)).any() and level < LEVELS:
            last = min(level + STEP, LEVELS)
            k = self.levels[level]
            x, y, n = count(self.scale(last), (k.x[kept], k.y[kept]), self.scale(level))
            for nxt in range(level + 1, last + 1):
                s = last - nxt
                both, back = np.unique((x >> s) + 1j * (y >> s), return_inverse=True)
                cx, cy, cn = both.real.astype(np.int64), both.imag.astype(np.int64), np.bincount(back.ravel(), weights=n).astype(np.int64)
                at = self.levels[nxt - 1].find(cx >> 1, cy >> 1)
                ok = at >= 0
                ok[ok] = self._split(nxt - 1)[at[ok]]
                self._add(nxt, cx[ok], cy[ok], cn[ok])
            level = last
        self._order()

    def scale(self, level: int) -> float:
        return 2.0 ** (level - self.exponent)

    def half(self, level: int) -> float:
        return 2.0 ** (self.exponent - level - 1)

    def _add(self, level, x, y, n):
        o = np.lexsort((y, x))
        self.levels[level] = Level(x[o], y[o], n[o], np.full(len(o), -1))

    def _split(self, level):
        """Cells that are cut: those that hold too much, and those beside one."""
        c = self.levels[level]
        out, big = np.zeros(len(c.x), bool), c.n > self.most
        if level >= LEVELS or not big.any():
            return out
        for dx, dy in _BESIDE:
            at = c.find(c.x + dx, c.y + dy)
            out |= (at >= 0) & big[at]
        return out

    def _order(self):
        """Numbers the leaves so that those below a cell follow each other."""
        cut = {k: self._split(k) for k in self.levels}
        self.levels = {k: c for k, c in self.levels.items() if len(c.x)}
        where = {k: {(x, y): i for i, (x, y) in enumerate(zip(c.x.tolist(), c.y.tolist(), strict=True))} for k, c in self.levels.items()}
        self.span = {k: np.zeros((len(c.x), 2), np.int64) for k, c in self.levels.items()}
        leaves = []
        todo = [(self.top, i, False) for i in reversed(range(len(self.levels[self.top].x)))]
        while todo:
            k, i, done = todo.pop()
            if done:
                self.span[k][i, 1] = len(leaves)
                continue
            c = self.levels[k]
            self.span[k][i, 0] = len(leaves)
            if not cut[k][i]:
                c.leaf[i] = len(leaves)
                leaves.append((k, i))
                self.span[k][i, 1] = len(leaves)
                continue
            todo.append((k, i, True))
            x, y = int(c.x[i]) * 2, int(c.y[i]) * 2
            todo += [(k + 1, j, False) for a in (1, 0) for b in (1, 0) if (j := where[k + 1].get((x + a, y + b))) is not None]
        self.leaves = np.array(leaves, np.int64).reshape(-1, 2)
        self.places = np.array([self.levels[k].n[i] for k, i in leaves], np.int64)

    def leaf_of(self, a, b):
        out = np.full(len(a), -1)
        for k, c in self.levels.items():
            rest = np.flatnonzero(out < 0)
            at = c.find(np.floor(a[rest] * self.scale(k)), np.floor(b[rest] * self.scale(k)))
            out[rest] = np.where(at >= 0, c.leaf[at], -1)
        return out

    def _compared(self, level, i, j):
        """Which pairs of cells of a level, neighbours or children of neighbours, are cut to get here: one of the parents holds too much."""
        if level == self.top:
            return np.ones(len(i), bool)
        c, up = self.levels[level], self.levels[level - 1]
        p, q = (up.find(c.x[k] >> 1, c.y[k] >> 1) for k in (i, j))
        return np.maximum(up.n[p], up.n[q]) > self.most

    def near(self):
        """For each leaf, the runs of leaves whose places are compared with its own."""
        out = [[] for _ in self.leaves]
        for k, c in self.levels.items():
            for dx, dy in _BESIDE:
                j = c.find(c.x + dx, c.y + dy)
                i = np.flatnonzero(j >= 0)
                j = j[i]
                ok = self._compared(k, i, j) & ((np.maximum(c.n[i], c.n[j]) <= self.most) | (k == LEVELS))
                for p, q in zip(self.span[k][i[ok]].tolist(), self.span[k][j[ok]].tolist(), strict=True):
                    for leaf in range(*p):
                        out[leaf].append(tuple(q))
        return [sorted(x) for x in out]

    def charge(self, leaf, rank, charges):
        """Takes the charges of the leaves (in parts, which add up) and adds up those of the cells above."""
        held: dict = {}
        for k in sorted(self.levels, reverse=True):
            c = self.levels[k]
            own = self.leaves[leaf, 0] == k
            cells, ranks, q = [self.leaves[leaf[own], 1]], [rank[own]], [charges[own]]
            if k + 1 in self.levels:
                d, below = held[k + 1], self.levels[k + 1]
                x, y = below.x[d[0]], below.y[d[0]]
                for a in (0, 1):
                    for b in (0, 1):
                        m = (x & 1 == a) & (y & 1 == b)
                        cells.append(c.find(x[m] >> 1, y[m] >> 1))
                        ranks.append(d[1][m])
                        q.append(np.einsum("ki,nkl,lj->nij", _HALVES[a], d[2][m], _HALVES[b], optimize=True))
            cells, ranks, q = np.concatenate(cells), np.concatenate(ranks), np.concatenate(q)
            both, back = np.unique(np.stack([cells, ranks]), axis=1, return_inverse=True)
            total = np.zeros((both.shape[1], NODES, NODES))
            np.add.at(total, back.ravel(), q)
            held[k] = (both[0], both[1], total)
            c.first, c.rank, c.charge = np.searchsorted(both[0], np.arange(len(c.x) + 1)), both[1], total

    def potentials(self, leaves, ranks: int):
        """The nodes' sums of each leaf from all cells far from it or from a cell above it, by rank."""
        from_top, out, kernels = {}, {}, {}
        want = {}
        for leaf in leaves:
            k, i = self.leaves[leaf]
            c = self.levels[k]
            x, y = int(c.x[i]), int(c.y[i])
            for up in range(k, self.top - 1, -1):
                want.setdefault(up, set()).add((x >> (k - up), y >> (k - up)))
        for k in sorted(want):
            c = self.levels[k]
            x, y = np.array(sorted(want[k]), np.int64).T
            t = c.find(x, y)
            v = np.zeros((len(t), ranks, NODES * NODES))
            if k > self.top:
                for dx in range(-3, 4):
                    for dy in range(-3, 4):
                        if max(abs(dx), abs(dy)) < 2:
                            continue
                        ok = (abs((x + dx >> 1) - (x >> 1)) < 2) & (abs((y + dy >> 1) - (y >> 1)) < 2)
                        i = np.flatnonzero(ok)
                        j = c.find(x[i] + dx, y[i] + dy)
                        i, j = i[j >= 0], j[j >= 0]
                        ok = self._compared(k, t[i], j)
                        i, j = i[ok], j[ok]
                        if not len(i):
                            continue
                        size = c.first[j + 1] - c.first[j]
                        rows = np.repeat(c.first[j] - np.cumsum(size) + size, size) + np.arange(size.sum())
                        if (dx, dy) not in kernels:
                            kernels[dx, dy] = _kernel(dx, dy)
                        v[np.repeat(i, size), c.rank[rows]] += c.charge[rows].reshape(len(rows), -1) @ kernels[dx, dy].T * self.half(k)
                up = from_top[k - 1]
                v = v.reshape(len(t), ranks, NODES, NODES)
                for n in range(len(t)):
                    v[n] += _HALVES[x[n] & 1] @ up[int(x[n]) >> 1, int(y[n]) >> 1] @ _HALVES[y[n] & 1].T
            from_top[k] = dict(zip(zip(x.tolist(), y.tolist(), strict=True), v.reshape(len(t), ranks, NODES, NODES), strict=True))
            for n, leaf in enumerate(c.leaf[t].tolist()):
                if leaf >= 0:
                    out[leaf] = from_top[k][int(x[n]), int(y[n])]
        return out

    def inside(self, leaf, a, b):
        """The nodes' polynomials of a leaf at places in it, along both axes."""
        k, i = self.leaves[leaf]
        c, s = self.levels[k], self.scale(k)
        return basis(2 * (a * s - c.x[i]) - 1), basis(2 * (b * s - c.y[i]) - 1)


def runs(values):
    """Start and end of runs of equal values."""
    cut = np.flatnonzero(np.diff(values)) + 1
    return list(zip([0, *cut.tolist()], [*cut.tolist(), len(values)], strict=True)) if len(values) else []


def leaf_rows(batches, cells):
    """Places (rank, a, b, n) with their leaf."""
    for t in batches:
        a, b = (t.column(c).to_numpy() for c in ("a", "b"))
        yield pa.RecordBatch.from_arrays([pa.array(cells.value.leaf_of(a, b), pa.int64()), *(t.column(c) for c in ("rank", "a", "b", "n"))], names=["leaf", "rank", "a", "b", "n"])


def leaf_charges(batches, cells):
    """Charges (leaf, rank, NODES x NODES numbers) of places in order of leaf and rank; a leaf in two batches gives two parts."""
    for t in batches:
        leaf, rank, a, b, n = (t.column(c).to_numpy() for c in ("leaf", "rank", "a", "b", "n"))
        rows = []
        for i, j in runs(leaf):
            x, y = cells.value.inside(leaf[i], a[i:j], b[i:j])
            x = x * n[i:j, None]
            for r in np.unique(rank[i:j]):
                own = rank[i:j] == r
                rows.append((leaf[i], r, (x[own].T @ y[own]).tobytes()))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, p) for c, p in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.binary()), strict=True)], names=["leaf", "rank", "charge"])


def silhouette_parts(batches, cells, group_of, near, ranks, size, odd):
    """rank, n, and mean distance to the others of its rank (a; null: there are none) and to the nearest other rank (b; null: there is none) of places, from rows (grp, leaf, rank, a, b, n) in order of group and leaf that hold for each group its leaves and all near them. size: rows of each rank; odd: what rows at no finite place add to sums."""
    names = ("leaf", "rank", "a", "b", "n")

    def whole(group, held):
        leaf, rank, a, b, n = (np.concatenate([h[c] for h in held]) for c in names)
        rank = np.searchsorted(ranks, rank)
        mine = np.flatnonzero(group_of.value == group).tolist()
        with np.errstate(over="ignore", invalid="ignore"):
            sums = list(place_sums(leaf, rank, a, b, n, cells.value, near.value, mine, len(ranks)))
        for at, total in sums:
            total += odd
            own, row = rank[at], np.arange(at.stop - at.start)
            with np.errstate(divide="ignore", invalid="ignore"):
                inner = total[row, own] / (size[own] - 1)
                total = total / size
            total[row, own] = np.nan
            outer = np.fmin.reduce(total, axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(ranks[own], pa.int32()), pa.array(n[at], pa.int64()), pa.array(inner, pa.float64(), mask=size[own] == 1), pa.array(outer, pa.float64(), mask=np.full(len(row), len(ranks) == 1))], names=["rank", "n", "a", "b"])

    group, held = None, []
    for t in batches:
        grp, rows = t.column("grp").to_numpy(), {c: t.column(c).to_numpy() for c in names}
        for i, j in runs(grp):
            if held and grp[i] != group:
                yield from whole(group, held)
                held = []
            group = grp[i]
            held.append({c: v[i:j] for c, v in rows.items()})
    if held:
        yield from whole(group, held)


def between(xa, xb, ya, yb, room):
    """Distances of places x (rows) to places y (columns), held in room until it is used again."""
    far, e = (r[: len(xa) * len(ya)].reshape(len(xa), len(ya)) for r in room)
    np.subtract(xa[:, None], ya, out=far)
    np.subtract(xb[:, None], yb, out=e)
    np.multiply(far, far, out=far)
    np.multiply(e, e, out=e)
    np.add(far, e, out=far)
    return np.sqrt(far, out=far)


def place_sums(leaf, rank, a, b, n, cells, near, mine, ranks: int):
    """The rows in the leaves named mine, and their summed distances to all places of each rank. All arrays are in order of leaf and hold every leaf near to mine."""
    weight = np.zeros((len(leaf), ranks))
    weight[np.arange(len(leaf)), rank] = n
    far = cells.potentials(mine, ranks)
    room = np.empty((2, TILE[0] * TILE[1]))
    for own in mine:
        i, j = np.searchsorted(leaf, (own, own + 1))
        at = np.concatenate([np.arange(*np.searchsorted(leaf, run)) for run in near[own]])
        sa, sb, sw = a[at], b[at], weight[at]
        x, y = cells.inside(own, a[i:j], b[i:j])
        total = np.einsum("nj,rnj->nr", y, x @ far[own])
        for p in range(i, j, TILE[0]):
            q = min(p + TILE[0], j)
            for s in range(0, len(at), TILE[1]):
                e = min(s + TILE[1], len(at))
                total[p - i : q - i] += between(a[p:q], b[p:q], sa[s:e], sb[s:e], room) @ sw[s:e]
        yield slice(i, j), total
