"""Candidate directions on the unit sphere as rationals over 2^20, and the candidates of a point."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frontfill.functions.lattice import SHIFT, SLACK, mix_point

K_DEFAULT = {1: 2, 2: 12, 3: 24}
ROTATIONS = 5


def directions(d: int, k: int | None = None, rotations: int = ROTATIONS) -> np.ndarray:
    """Shape (rotations, k, d): ``rotations`` turned copies of ``k`` even directions."""
    k = k or K_DEFAULT.get(d, 8 * d)
    scale = 1 << SHIFT
    out = np.zeros((rotations, k, d), np.int64)
    if d == 1:
        out[:, :, 0] = [scale if i % 2 == 0 else -scale for i in range(k)]
    elif d == 2:
        for r in range(rotations):
            for i in range(k):
                t = 2 * math.pi * (rotations * i + r) / (rotations * k)
                out[r, i] = round(scale * math.cos(t)), round(scale * math.sin(t))
    elif d == 3:
        golden = math.pi * (3 - math.sqrt(5))
        for r in range(rotations):
            for i in range(k):
                z = 1 - (2 * i + 1) / k
                t = golden * i + 2 * math.pi * r / rotations
                s = math.sqrt(1 - z * z)
                out[r, i] = round(scale * s * math.cos(t)), round(scale * s * math.sin(t)), round(scale * z)
    else:
        for r in range(rotations):
            for i in range(k):
                u = [(mix_point([r + 1, i + 1, a + 1, s]) + 0.5) / 2147483647 for a in range(d) for s in (1, 2)]
                g = [math.sqrt(-2 * math.log(u[2 * a])) * math.cos(2 * math.pi * u[2 * a + 1]) for a in range(d)]
                n = math.sqrt(sum(x * x for x in g))
                out[r, i] = [round(scale * x / n) for x in g]
    if d > 2:
        # rounded directions must not be short: the slack covers two axes' error only
        while (short := (out * out).sum(axis=2) < scale * scale).any():
            r, i = np.nonzero(short)
            a = np.abs(out[r, i]).argmax(axis=1)
            out[r, i, a] += np.sign(out[r, i, a])
    return out


def propose(x: np.ndarray, h: np.ndarray, dirs: np.ndarray, annulus: bool = False) -> np.ndarray:
    """Candidates of points ``x`` (n, d) with spacings ``h``: (n, k, d), in the fixed order.

    ``annulus`` draws each radius from h..2h by the point's hash instead of the sphere itself.
    """
    turn = mix_point([x[:, a] for a in range(x.shape[1])])
    reach = (h + SLACK)[:, None]
    if annulus:
        k = np.arange(dirs.shape[1])[None, :]
        reach = reach + h[:, None] * (mix_point([turn[:, None] + k, k]) % 1024) // 1024
    steps = dirs[turn % dirs.shape[0]]
    return ((x[:, None, :] << SHIFT) + reach[:, :, None] * steps + (1 << (SHIFT - 1))) >> SHIFT


def candidates(points: DataFrame, d: int, k: int | None = None, rotations: int = ROTATIONS, h_col: str = "h") -> DataFrame:
    """All candidates of each point as rows (``k``, ``c0..``): native expressions over the literal direction table."""
    dirs = directions(d, k, rotations)
    xs = [F.col(f"x{a}") for a in range(d)]
    turn = F.pmod(mix_point(xs), F.lit(rotations)).cast("int")
    table = F.array(*(F.array(*(F.array(*(F.lit(int(v)) for v in dirs[r, i])) for i in range(dirs.shape[1]))) for r in range(rotations)))
    rows = points.select("*", F.posexplode(F.get(table, turn)).alias("k", "dir"))

    def at(a: int) -> Column:
        raw = F.shiftleft(F.col(f"x{a}"), SHIFT) + (F.col(h_col) + F.lit(SLACK)) * F.col("dir")[a] + F.lit(1 << (SHIFT - 1))
        return F.shiftright(raw, SHIFT)

    return rows.select(*points.columns, "k", *(at(a).alias(f"c{a}") for a in range(d)))
