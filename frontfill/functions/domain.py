"""Regions as membership predicates: a Column for Catalyst and an array twin for kernels.

A region is a tree of primitives combined by ``&``, ``|`` and ``-``; both twins come from one definition, so they
cannot disagree.  Bounding boxes are added as plain range conjuncts that reach the Parquet scan.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import and_

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from frontfill.functions.lattice import CENTRE, RADIUS


class Domain:
    def test(self, xs):
        """Membership of coordinates given one Column or array an axis."""
        raise NotImplementedError

    def box(self) -> list[tuple[int, int]] | None:
        """Inclusive bounds on each axis, where known."""
        return None

    def column(self, names: list[str]) -> Column:
        xs = [F.col(n) for n in names]
        inside = self.test(xs)
        if (b := self.box()) is not None:
            inside = reduce(and_, ((x >= F.lit(lo)) & (x <= F.lit(hi)) for x, (lo, hi) in zip(xs, b, strict=True))) & inside
        return inside

    def mask(self, x: np.ndarray) -> np.ndarray:
        return self.test([x[..., a] for a in range(x.shape[-1])])

    def __and__(self, other):
        return Combined("and", self, other)

    def __or__(self, other):
        return Combined("or", self, other)

    def __sub__(self, other):
        return Combined("minus", self, other)


@dataclass
class Combined(Domain):
    how: str
    a: Domain
    b: Domain

    def test(self, xs):
        p, q = self.a.test(xs), self.b.test(xs)
        return (p & q) if self.how == "and" else (p | q) if self.how == "or" else (p & ~q)

    def box(self):
        p, q = self.a.box(), self.b.box()
        if self.how == "minus":
            return p
        if self.how == "and":
            if p is None or q is None:
                return p or q
            return [(max(a, c), min(b, e)) for (a, b), (c, e) in zip(p, q, strict=True)]
        return None if p is None or q is None else [(min(a, c), max(b, e)) for (a, b), (c, e) in zip(p, q, strict=True)]


@dataclass
class Ball(Domain):
    centre: tuple[int, ...]
    radius: int

    def test(self, xs):
        return reduce(lambda s, t: s + t, ((x - c) * (x - c) for x, c in zip(xs, self.centre, strict=True))) <= self.radius * self.radius

    def box(self):
        return [(c - self.radius, c + self.radius) for c in self.centre]


@dataclass
class Box(Domain):
    lo: tuple[int, ...]
    hi: tuple[int, ...]

    def test(self, xs):
        return reduce(and_, ((x >= a) & (x <= b) for x, a, b in zip(xs, self.lo, self.hi, strict=True)))

    def box(self):
        return list(zip(self.lo, self.hi, strict=True))


@dataclass
class HalfSpace(Domain):
    """Points with ``normal . x <= bound``."""

    normal: tuple[int, ...]
    bound: int

    def test(self, xs):
        return reduce(lambda s, t: s + t, (x * n for x, n in zip(xs, self.normal, strict=True))) <= self.bound


@dataclass
class Polygon(Domain):
    """Even-odd rule by crossing edges, in exact integer arithmetic; two axes."""

    corners: tuple[tuple[int, int], ...]

    def test(self, xs):
        x, y = xs
        odd = None
        for (x0, y0), (x1, y1) in zip(self.corners, self.corners[1:] + self.corners[:1], strict=True):
            if y0 == y1:
                continue
            if y0 > y1:
                x0, y0, x1, y1 = x1, y1, x0, y0
            # the edge spans the point's height and lies to its right
            hit = (y >= y0) & (y < y1) & ((x - x0) * (y1 - y0) < (y - y0) * (x1 - x0))
            odd = hit if odd is None else (odd != hit)
        return odd

    def box(self):
        return [(min(c[a] for c in self.corners), max(c[a] for c in self.corners)) for a in range(2)]


def annulus(centre: tuple[int, ...], inner: int, outer: int) -> Domain:
    return Ball(centre, outer) - Ball(centre, inner)


def disc(radius: int = RADIUS, d: int = 2) -> Ball:
    return Ball((CENTRE,) * d, radius)


def in_cells(df, cells, names: list[str], level: int):
    """Rows whose work cell occurs in a table of tagged keys: membership by a semi-join."""
    from frontfill.functions.lattice import BITS, cell_key

    here = [F.shiftright(F.col(n), BITS - level) for n in names]
    keyed = df.withColumn("__cell", cell_key(here, F.lit(level), len(names)))
    return keyed.join(cells.select(F.col("cell").alias("__cell")).distinct(), "__cell", "left_semi").drop("__cell")
