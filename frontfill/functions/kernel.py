"""The advancing-front kernel: exact first-in-first-out filling in array operations.

The front is expanded in waves.  A wave holds every unexpanded point in queue order; its candidates, in parent order and then
direction order, are what a one-by-one fill would test next, because children only ever join the end of the queue.  Within the wave a
candidate is accepted iff no accepted point, earlier candidates of the wave included, is nearer than its parent's spacing.
That greedy answer is found by rounds: a candidate whose earlier rivals are all settled is settled itself; where a round settles few,
because candidates wait for one another in long chains, the rest are taken in order.  Cells that
cannot influence one another may share a wave, so one call fills all cells of a task at once.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from frontfill.functions.directions import propose
from frontfill.functions.lattice import SLACK


class Grid:
    """Points hashed to cubes of one side, kept in key order; neighbours by ranges of keys."""

    def __init__(self, d: int, side: int):
        self.d, self.side = d, max(1, side)
        self.bits = 62 // d
        self.keys = np.zeros(0, np.int64)
        self.rows = np.zeros(0, np.int64)

    def _cells(self, x: np.ndarray) -> np.ndarray:
        return x // self.side + 2

    def _key(self, c: np.ndarray) -> np.ndarray:
        k = c[..., 0]
        for a in range(1, self.d):
            k = (k << self.bits) | c[..., a]
        return k

    def add(self, x: np.ndarray, first_row: int) -> None:
        k = self._key(self._cells(x))
        order = np.argsort(k, kind="stable")
        k = k[order]
        at = np.searchsorted(self.keys, k, side="right")
        self.keys = np.insert(self.keys, at, k)
        self.rows = np.insert(self.rows, at, order + first_row)

    def take(self, other: Grid) -> None:
        """Move the rows of another grid of the same side here."""
        at = np.searchsorted(self.keys, other.keys, side="right")
        self.keys = np.insert(self.keys, at, other.keys)
        self.rows = np.insert(self.rows, at, other.rows)
        other.keys, other.rows = other.keys[:0], other.rows[:0]

    def near(self, x: np.ndarray, rings: int = 1) -> tuple[np.ndarray, np.ndarray]:
        """(query, row) pairs of all points in the cubes within ``rings`` of each query's cube."""
        c = self._cells(x)
        q_all, r_all = [], []
        span = range(-rings, rings + 1)
        shifts = [()]
        for _ in range(self.d - 1):
            shifts = [(*s, o) for s in shifts for o in span]
        # in key order, searches next to one another touch the same keys
        base = np.argsort(self._key(c))
        c = c[base]
        for s in shifts:
            lo = c.copy()
            for a, o in enumerate(s):
                lo[:, a] += o
            lo[:, -1] -= rings
            k = self._key(lo)
            i, j = np.searchsorted(self.keys, k), np.searchsorted(self.keys, k + 2 * rings, side="right")
            n = j - i
            total = int(n.sum())
            if total:
                q = np.repeat(base, n)
                r_all.append(self.rows[np.repeat(i - (np.cumsum(n) - n), n) + np.arange(total)])
                q_all.append(q)
        if not q_all:
            z = np.zeros(0, np.int64)
            return z, z
        return np.concatenate(q_all), np.concatenate(r_all)


class Spots:
    """Points of one spacing, looked up without a search: cells so small that each holds one point at most, and a table of all cells of a box.

    The table costs four bytes a cell, so it is for boxes that the points fill evenly.  All points that can be too near to a candidate
    of a parent are fetched once a parent, not once a candidate.
    """

    def __init__(self, box: list[tuple[int, int]], h: int):
        self.d, self.side, self.cell = len(box), h, self.small(h, len(box))
        #: a candidate is SLACK, a rounding and an error of its direction farther than ``h`` from its parent at most
        self.span = 2 * h + SLACK + 2 + (h >> 16)
        rings = -(-self.span // self.cell)
        self.lo = [lo - rings * self.cell for lo, _ in box]
        self.shape = [(hi - lo) // self.cell + 1 + 2 * rings for lo, hi in box]
        #: row and one; 0: no point
        self.table = np.zeros(math.prod(self.shape), np.int32)
        o = np.array(list(np.ndindex(*([2 * rings + 1] * self.d))), np.int64) - rings
        least = np.where(o == 0, 0, (np.abs(o) - 1) * self.cell + 1)
        o = o[(least**2).sum(axis=1) <= self.span**2]
        self.around = np.array([self._flat(list(v)) for v in o], np.int64)
        self.n = 0

    @staticmethod
    def small(h: int, d: int) -> int:
        """The widest cell in which no two points are ``h`` apart."""
        return math.isqrt((h * h - 1) // d) + 1

    def _flat(self, c):
        k = c[0]
        for a in range(1, self.d):
            k = k * self.shape[a] + c[a]
        return k

    def _at(self, x: np.ndarray) -> np.ndarray:
        return self._flat([(x[:, a] - self.lo[a]) // self.cell for a in range(self.d)])

    def add(self, x: np.ndarray, first_row: int) -> None:
        self.table[self._at(x)] = np.arange(first_row + 1, first_row + len(x) + 1)
        self.n += len(x)

    def taken(self, cand: np.ndarray, x: np.ndarray, parent: np.ndarray) -> np.ndarray:
        """Which candidates are nearer than ``h`` to a point; candidates of one parent, a row of ``x``, stand side by side."""
        first = np.flatnonzero(np.diff(parent, prepend=-1))
        out = np.zeros(len(cand), bool)
        for i in range(0, len(first), 1024):
            at = first[i : i + 1024]
            end = int(first[i + 1024]) if i + 1024 < len(first) else len(cand)
            out[at[0] : end] = self._taken(cand[at[0] : end], x, x[parent[at]].astype(np.int64), at - at[0])
        return out

    def _taken(self, cand: np.ndarray, x: np.ndarray, px: np.ndarray, first: np.ndarray) -> np.ndarray:
        many = np.diff(first, append=len(cand))
        k = int(many.max())
        of = np.repeat(np.arange(len(first)), many)
        place = of * k + np.arange(len(cand)) - first[of]
        rows = self.table.take(self._at(px)[:, None] + self.around).ravel()
        at = np.flatnonzero(rows != 0)
        p = at // len(self.around)
        gap = (x.take(rows[at] - 1, axis=0) - px.take(p, axis=0)).astype(np.float64)
        # differences are under 2^25, so their squares and sums are whole in doubles
        near = np.flatnonzero((gap * gap).sum(axis=1) <= float(self.span) ** 2)
        p, gap = p[near], gap[near]
        square = 0.0
        for a in range(self.d):
            # where a parent has fewer candidates the places left over are far from all points
            to = np.full(len(first) * k, 4.0 * self.span)
            to[place] = cand[:, a] - px[of, a]
            g = to.reshape(-1, k).take(p, axis=0)
            g -= gap[:, a, None]
            g *= g
            square += g
        hit = np.flatnonzero((square < float(self.side) ** 2).ravel())
        pair = hit // k
        bad = np.zeros(len(first) * k, bool)
        bad[hit + ((p - np.arange(len(p))) * k)[pair]] = True
        return bad[place]


class Tiers:
    """A :class:`Grid` for many small additions: grids of growing size, each emptied into the next when it is full."""

    FIRST, GROWTH = 4096, 32

    def __init__(self, d: int, side: int):
        self.d, self.side = d, max(1, side)
        self.tiers = [Grid(d, side)]

    @property
    def keys(self) -> np.ndarray:
        return max((t.keys for t in self.tiers), key=len)

    def add(self, x: np.ndarray, first_row: int) -> None:
        self.tiers[0].add(x, first_row)
        most = self.FIRST
        for i, t in enumerate(self.tiers):
            if len(t.keys) <= most:
                break
            if i + 1 == len(self.tiers):
                self.tiers.append(Grid(self.d, self.side))
            self.tiers[i + 1].take(t)
            most *= self.GROWTH

    def near(self, x: np.ndarray, rings: int = 1) -> tuple[np.ndarray, np.ndarray]:
        got = [t.near(x, rings) for t in self.tiers if len(t.keys)]
        if not got:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        return np.concatenate([q for q, _ in got]), np.concatenate([r for _, r in got])


@dataclass
class Filled:
    """New points in order of acceptance: coordinates, spacing, radius they were tested with, parent row, wave."""

    x: np.ndarray
    h: np.ndarray
    h_parent: np.ndarray
    parent: np.ndarray
    tested: int
    outside: int
    blocked: int
    waves: int


def squared_gap(a: np.ndarray, q: np.ndarray, b: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Squared distances of rows ``q`` of ``a`` to rows ``r`` of ``b``, an axis at a time."""
    out = np.zeros(len(q), np.int64)
    for i in range(a.shape[1]):
        g = a[q, i] - b[r, i].astype(np.int64, copy=False)
        out += g * g
    return out


def rivals(c: np.ndarray, radius: np.ndarray, side: int, rings: int) -> tuple[np.ndarray, np.ndarray]:
    """(later, earlier) pairs of candidates nearer to one another than the later one's radius."""
    d = c.shape[1]
    own = Grid(d, side)
    own.add(c, 0)
    keys, rows = own.keys, own.rows
    x, cells = c[rows], own._cells(c[rows])
    # each pair once: the cubes after a candidate's own in key order
    half = [s for s in np.ndindex(*([2 * rings + 1] * (d - 1))) if s >= (rings,) * (d - 1)]
    q_all, r_all = [], []
    for s in half:
        to = cells.copy()
        to[:, : d - 1] += np.array(s, np.int64) - rings
        k = own._key(to)
        i = np.arange(1, len(c) + 1) if s == (rings,) * (d - 1) else np.searchsorted(keys, k - rings)
        n = np.searchsorted(keys, k + rings, side="right") - i
        q = np.repeat(np.arange(len(c)), n)
        r = np.repeat(i - (np.cumsum(n) - n), n) + np.arange(len(q))
        gap = squared_gap(x, q, x, r)
        q, r = rows[q], rows[r]
        q, r = np.maximum(q, r), np.minimum(q, r)
        hit = gap < radius[q] ** 2
        q_all.append(q[hit])
        r_all.append(r[hit])
    return np.concatenate(q_all), np.concatenate(r_all)


def settle(cand: np.ndarray, radius: np.ndarray, grid: Grid | Tiers | Spots, x: np.ndarray, rings: int, parent: np.ndarray | None = None) -> np.ndarray:
    """Which candidates, taken in order, are accepted against the points of the grid and one another (``parent``: their parents' rows, for :class:`Spots`)."""
    n = len(cand)
    ok = np.ones(n, bool)
    if isinstance(grid, Spots):
        if n and grid.n:
            ok = ~grid.taken(cand, x, parent)
    elif len(grid.keys):
        q, r = grid.near(cand, rings)
        ok[q[squared_gap(cand, q, x, r) < radius[q] ** 2]] = False
    live = np.flatnonzero(ok)
    if not len(live):
        return ok
    q, r = rivals(cand[live], radius[live], grid.side, rings)
    ok[live] = in_order(len(live), q, r)
    return ok


def in_order(n: int, q: np.ndarray, r: np.ndarray) -> np.ndarray:
    """Which of ``n`` candidates are accepted one after another, where ``q`` is out if the earlier ``r`` is in."""
    open_, good = np.ones(n, bool), np.zeros(n, bool)
    left = n
    while len(q):
        now = open_.copy()
        now[q] = False
        good |= now
        open_ &= ~now
        open_[q[now[r]]] = False
        keep = open_[q] & open_[r]
        q, r = q[keep], r[keep]
        was, left = left, int(open_.sum())
        if 8 * left > 7 * was:
            break
    if len(q):
        # candidates in chains: one round settles a link of each
        by = np.argsort(r, kind="stable")
        q, r = q[by], r[by]
        at = np.flatnonzero(np.diff(r, prepend=-1))
        out, later = bytearray(n), q.tolist()
        for i, a, b in zip(r[at].tolist(), at.tolist(), [*at[1:].tolist(), len(q)], strict=True):
            if not out[i]:
                for j in later[a:b]:
                    out[j] = 1
        open_ &= np.frombuffer(out, np.uint8) == 0
    return good | open_


def front_fill(
    x: np.ndarray,
    front: np.ndarray,
    h_at,
    inside,
    dirs: np.ndarray,
    h_most: int,
    owned=None,
    annulus: bool = False,
    limit: int | None = None,
    order: str = "fifo",
) -> Filled:
    """Expand the points ``front`` (row numbers of ``x``, in queue order) until the front is empty.

    ``h_at`` and ``inside`` map coordinates to spacing and membership.  ``owned(child, parent_row)`` tells which accepted
    children may be expanded here; the others are only stored.  ``limit`` bounds the number of expanded points.
    ``order`` takes the front first-in-first-out, or one at a time last-in-first-out or by hash (``lifo``, ``random``).
    """
    d = x.shape[1]
    rings = 2 if annulus else 1
    grid = Grid(d, h_most)
    grid.add(x, 0)
    cap = max(1024, 2 * len(x))
    pts = np.zeros((cap, d), np.int64)
    pts[: len(x)] = x
    n0 = n = len(x)
    hp, par = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    tested = outside = blocked = waves = done = 0
    queue = np.asarray(front, np.int64)
    while len(queue) and (limit is None or done < limit):
        if order == "fifo":
            take = len(queue) if limit is None else min(len(queue), limit - done)
            now, queue = queue[:take], queue[take:]
        else:
            at = len(queue) - 1 if order == "lifo" else int((int(pts[queue[0], 0]) * 48271 + n) % len(queue))
            now, queue = queue[at : at + 1], np.delete(queue, at)
        done += len(now)
        waves += 1
        px = pts[now]
        ph = h_at(px)
        cand = propose(px, ph, dirs, annulus)
        k = cand.shape[1]
        cand = cand.reshape(-1, d)
        parent, radius = np.repeat(now, k), np.repeat(ph, k)
        tested += len(cand)
        inn = inside(cand)
        outside += int((~inn).sum())
        cand, parent, radius = cand[inn], parent[inn], radius[inn]
        ok = settle(cand, radius, grid, pts, 1)
        blocked += int((~ok).sum())
        cand, parent, radius = cand[ok], parent[ok], radius[ok]
        m = len(cand)
        if not m:
            continue
        while n + m > cap:
            cap *= 2
            pts = np.concatenate([pts, np.zeros_like(pts)])[:cap]
        pts[n : n + m] = cand
        grid.add(cand, n)
        mine = np.ones(m, bool) if owned is None else owned(cand, parent)
        queue = np.concatenate([queue, np.arange(n, n + m)[mine]])
        hp.append(radius)
        par.append(parent)
        n += m
    new = pts[n0:n].copy()
    return Filled(new, h_at(new), np.concatenate(hp), np.concatenate(par), tested, outside, blocked, waves)
