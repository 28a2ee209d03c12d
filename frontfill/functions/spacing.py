"""Spacing functions in lattice units: constant, linear, radial, stepped; Column and array twins."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


class Spacing:
    least: int
    most: int

    def at(self, x: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def column(self, names: list[str]) -> Column:
        raise NotImplementedError


@dataclass
class Constant(Spacing):
    h: int

    def __post_init__(self):
        if self.h < 4:
            raise ValueError("spacing under four lattice units")
        self.least = self.most = self.h

    def at(self, x):
        return np.full(x.shape[:-1], self.h, np.int64)

    def column(self, names):
        return F.lit(self.h).cast("long")


@dataclass
class Linear(Spacing):
    """``h0`` at coordinate 0 of an axis, ``h1`` at the far face."""

    h0: int
    h1: int
    axis: int = 0
    shift: int = 24

    def __post_init__(self):
        self.least, self.most = sorted((self.h0, self.h1))

    def at(self, x):
        return self.h0 + ((x[..., self.axis] * (self.h1 - self.h0)) >> self.shift)

    def column(self, names):
        return F.lit(self.h0) + F.shiftright(F.col(names[self.axis]) * F.lit(self.h1 - self.h0), self.shift)


@dataclass
class Radial(Spacing):
    """Grows with the squared distance from a centre, from ``h0`` to ``h1`` at ``reach``."""

    centre: tuple[int, ...]
    h0: int
    h1: int
    reach: int

    def __post_init__(self):
        self.least, self.most = sorted((self.h0, self.h1))

    def at(self, x):
        s = sum((x[..., a] - c) ** 2 for a, c in enumerate(self.centre))
        q = np.minimum(s // max(1, self.reach * self.reach >> 20), 1 << 20)
        return self.h0 + ((q * (self.h1 - self.h0)) >> 20)

    def column(self, names):
        s = None
        for n, c in zip(names, self.centre, strict=True):
            t = (F.col(n) - c) * (F.col(n) - c)
            s = t if s is None else s + t
        q = F.least(F.call_function("div", s, F.lit(max(1, self.reach * self.reach >> 20))), F.lit(1 << 20))
        return F.lit(self.h0) + F.shiftright(q * F.lit(self.h1 - self.h0), 20)


@dataclass
class Step(Spacing):
    """``below`` under a threshold on one axis, ``above`` from it on."""

    axis: int
    at_value: int
    below: int
    above: int

    def __post_init__(self):
        self.least, self.most = sorted((self.below, self.above))

    def at(self, x):
        return np.where(x[..., self.axis] < self.at_value, self.below, self.above).astype(np.int64)

    def column(self, names):
        return F.when(F.col(names[self.axis]) < self.at_value, F.lit(self.below)).otherwise(F.lit(self.above)).cast("long")


@dataclass
class FromCells(Spacing):
    """Spacing by uniform cell of a level; cells without a value take ``default``."""

    level: int
    values: dict = field(default_factory=dict)
    default: int = 1 << 20
    bits: int = 24

    def __post_init__(self):
        every = [*self.values.values(), self.default]
        self.least, self.most = min(every), max(every)
        keys = sorted(self.values)
        self._keys = np.array(keys, np.int64)
        self._h = np.array([self.values[k] for k in keys], np.int64)

    def at(self, x):
        from frontfill.functions.lattice import key_array

        k = key_array([x[..., a] >> (self.bits - self.level) for a in range(x.shape[-1])], self.level)
        i = np.searchsorted(self._keys, k)
        i = np.minimum(i, max(0, len(self._keys) - 1))
        return np.where(self._keys[i] == k, self._h[i], self.default) if len(self._keys) else np.full(x.shape[:-1], self.default, np.int64)

    def column(self, names):
        if not self.values:
            return F.lit(self.default).cast("long")
        d, shift = len(names), self.bits - self.level
        flat = {}
        for key, h in self.values.items():
            code = key - (1 << (d * self.level))
            c = [sum(((code >> (d * b + d - 1 - a)) & 1) << b for b in range(self.level)) for a in range(d)]
            flat[sum(v << (self.level * (d - 1 - a)) for a, v in enumerate(c))] = h
        here = None
        for a, n in enumerate(names):
            t = F.shiftleft(F.shiftright(F.col(n), shift), self.level * (d - 1 - a))
            here = t if here is None else here.bitwiseOR(t)
        # a value a cell of a fixed level: a literal array by row-major place, the default elsewhere
        table = F.array(*(F.lit(flat.get(i, self.default)).cast("long") for i in range(1 << (d * self.level))))
        return F.coalesce(F.get(table, here.cast("int")), F.lit(self.default).cast("long"))
