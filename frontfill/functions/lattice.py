"""Integer lattice on which all geometry is exact: snapping, size rules, hashes, cell keys.

The root cube is ``[0, 2^24)`` on each axis.  Coordinates, spacings and squared distances are LONG, so acceptance tests give the
same answer in Spark expressions, NumPy and SQL.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 24
SIDE = 1 << BITS
CENTRE = SIDE // 2
RADIUS = 6_000_000
SHIFT = 20
SLACK = 3
PRIME = 2_147_483_647


def max_level(d: int) -> int:
    """Deepest tree level whose tagged key fits a LONG."""
    return min(BITS, 60 // d)


def size_h(n: int) -> int:
    """Spacing at which a disc of the standard radius holds about ``n`` points."""
    return int(math.floor(float(RADIUS) * math.sqrt(2.8 / n)))


def size_h3(n: int) -> int:
    return int(math.floor(float(RADIUS) * (3.4 / n) ** (1.0 / 3)))


def axis(raw: Column, lo: int, span: int) -> Column:
    """Affine map of an integer column onto the lattice, clamped."""
    scaled = (raw - F.lit(lo)).cast("long") * F.lit(SIDE)
    v = F.call_function("div", scaled, F.lit(span).cast("long"))
    return F.greatest(F.lit(0), F.least(F.lit(SIDE - 1), v.cast("long")))


def cents(c: Column) -> Column:
    return F.round(c * 100 + 0.0).cast("long")


def mix(k):
    """Portable hash step on non-negative integers: Columns, arrays or ints alike."""
    if isinstance(k, Column):
        return F.pmod(k * F.lit(48271) + F.lit(11), F.lit(PRIME))
    return (k * 48271 + 11) % PRIME


def mix_point(xs):
    """Chained hash of coordinates."""
    return reduce(lambda a, x: mix(a + x), xs[1:], mix(xs[0]))


def priority(id_: Column) -> Column:
    return mix(mix(id_))


def squared(xs: list[Column], ys: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, ((x - y) * (x - y) for x, y in zip(xs, ys, strict=True)))


def spread(c, d: int, bits: int):
    """Bits of ``c`` set ``d`` apart, by halving block moves; works on Columns and arrays."""
    if d == 1:
        return c
    sql = isinstance(c, Column)
    left = (lambda x, n: F.shiftleft(x, n)) if sql else (lambda x, n: x << n)
    both = (lambda x, m: x.bitwiseAND(F.lit(m))) if sql else (lambda x, m: x & m)
    either = (lambda x, y: x.bitwiseOR(y)) if sql else (lambda x, y: x | y)
    width = 1 << max(0, (bits - 1).bit_length())
    while width > 1:
        half = width // 2
        mask = 0
        for b in range(0, 64 // d + 1, half):
            if b < bits:
                mask |= ((1 << half) - 1) << (b * d)
        mask &= (1 << 63) - 1
        c = both(either(c, left(c, half * (d - 1))), mask)
        width = half
    return c


def morton(cells, level_bits: int):
    """Interleave cell coordinates; the first axis holds the higher bit of each group."""
    d = len(cells)
    sql = isinstance(cells[0], Column)
    out = None
    for a, c in enumerate(cells):
        s = spread(c, d, level_bits)
        n = d - 1 - a
        s = (F.shiftleft(s, n) if sql else s << n) if n else s
        out = s if out is None else (out.bitwiseOR(s) if sql else out | s)
    return out


def cell_key(cells: list[Column], level: Column, d: int) -> Column:
    """Level-tagged key: a leading one, then the interleaved coordinates."""
    tag = F.expr("1L")
    one = F.call_function("shiftleft", tag, (level * F.lit(d)).cast("int"))
    return one.bitwiseOR(morton(cells, max_level(d)))


def key_array(cells: list[np.ndarray], level: int) -> np.ndarray:
    return (1 << (len(cells) * level)) | morton([c.astype(np.int64) for c in cells], max_level(len(cells)))
