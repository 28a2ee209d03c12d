"""Work trees as linear tables of leaves: build, neighbours, colours, levels, balance.

A leaf is a row ``cell, level, c0.., lo0.., side, est``; its key is the Morton code of its place under a leading one, so parents are
shifts and ranges of keys are subtrees.  Everything is equi-joins and partial aggregations on keys.
"""

from __future__ import annotations

from functools import reduce
from itertools import product
from operator import and_

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frontfill.functions.lattice import BITS, SIDE, cell_key, key_array, max_level, morton
from frontfill.sources.store import stored

#: points of a fill for each unit of volume over h^d, measured
DENSITY = {1: 1.0, 2: 0.89, 3: 0.81}


def _axes(df: DataFrame, prefix: str = "x") -> list[str]:
    return sorted((c for c in df.columns if c[: len(prefix)] == prefix and c[len(prefix) :].isdigit()), key=lambda c: int(c[len(prefix) :]))


def point_key(names: list[str], level: int) -> Column:
    """Key of the cell of a level that holds a point."""
    return cell_key([F.shiftright(F.col(n), BITS - level) for n in names], F.lit(level), len(names))


def _uncode(key: Column, level: Column, d: int) -> list[Column]:
    """Cell coordinates of a tagged key: every d-th bit, gathered by summing."""
    deep = max_level(d)
    out = []
    for a in range(d):
        bits = [F.shiftleft(F.shiftright(key, d * b + d - 1 - a).bitwiseAND(F.lit(1).cast("long")), b) for b in range(deep)]
        # the tag's bit lies at d * level: mask it out
        out.append(reduce(lambda p, q: p.bitwiseOR(q), bits).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), level.cast("int")) - 1))
    return out


def with_boxes(cells: DataFrame, d: int) -> DataFrame:
    """Add cell coordinates, lower corner and side from key and level."""
    xs = _uncode(F.col("cell"), F.col("level"), d)
    side = F.call_function("shiftleft", F.lit(1).cast("long"), (F.lit(BITS) - F.col("level")).cast("int"))
    out = cells.withColumns({f"c{a}": x for a, x in enumerate(xs)})
    return out.withColumns({**{f"lo{a}": F.col(f"c{a}") * side for a in range(d)}, "side": side})


def build_counted(points: DataFrame, limit: int, deepest: int | None = None, coarsest: int = 0, names: list[str] | None = None) -> DataFrame:
    """Leaves of the tree that splits every cell with more than ``limit`` points: ``cell, level, est``, empty ones too.

    Rows are counted once at the deepest level; coarser levels are sums of those counts, so one pass serves all levels.
    """
    names = names or _axes(points)
    d = len(names)
    deep = min(deepest if deepest is not None else max_level(d), max_level(d))
    finest = points.where(reduce(and_, (F.col(n).isNotNull() for n in names))).groupBy(point_key(names, deep).alias("key")).agg(F.count("*").alias("n"))
    levels = finest.select(F.explode(F.sequence(F.lit(coarsest), F.lit(deep))).alias("level"), "key", "n")
    up = F.call_function("shiftright", F.col("key"), (F.lit(d) * (F.lit(deep) - F.col("level"))).cast("int"))
    nodes = levels.select("level", up.alias("cell"), "n").groupBy("cell", "level").agg(F.sum("n").alias("est"))
    split = (F.col("est") > limit) & (F.col("level") < deep)
    children = _children(nodes.where(split), d)
    roots = points.sparkSession.range(1 << (d * coarsest)).select((F.col("id") + (1 << (d * coarsest))).alias("cell"), F.lit(coarsest).alias("level"))
    every = roots.union(children)
    known = nodes.select("cell", F.col("est"), split.alias("split"))
    # sides that grow with the rows are merged: their shuffled size hides what a broadcast would hold
    leaves = every.join(known.hint("merge"), "cell", "left").where(~F.coalesce("split", F.lit(False)))
    return leaves.select("cell", F.col("level").cast("int").alias("level"), F.coalesce("est", F.lit(0)).cast("long").alias("est"))


def _children(cells: DataFrame, d: int) -> DataFrame:
    each = cells.select("cell", "level", F.explode(F.sequence(F.lit(0), F.lit((1 << d) - 1))).alias("o"))
    return each.select((F.shiftleft(F.col("cell"), d) + F.col("o")).alias("cell"), (F.col("level") + 1).cast("int").alias("level"))


def uniform(spark, level: int, d: int) -> DataFrame:
    """All cells of one level."""
    tag = 1 << (d * level)
    return spark.range(tag).select((F.col("id") + tag).alias("cell"), F.lit(level).cast("int").alias("level"))


def uniform_level(limit: int, h: int, d: int) -> int:
    """Level of the full tree for a constant spacing: split while the estimate is over the limit and the cells stay wide enough."""
    level = 0
    while level < max_level(d):
        side = SIDE >> level
        if DENSITY.get(d, 0.7) * (side / h) ** d <= limit or (side >> 1) < 3 * h + 6:
            break
        level += 1
    return level


def estimate(cells: DataFrame, spacing, d: int, domain=None, q: int = 4) -> DataFrame:
    """Expected points of each cell: density times the mean of ``h^-d`` over ``q`` midpoints an axis, clipped to a region."""
    boxed = with_boxes(cells, d)
    step = [F.explode(F.sequence(F.lit(0), F.lit(q - 1))).alias(f"q{a}") for a in range(d)]
    rows = boxed
    for s, a in zip(step, range(d), strict=True):
        rows = rows.select("*", s)
    rows = rows.withColumns({f"x{a}": (F.col(f"lo{a}") + F.call_function("div", F.col("side") * (2 * F.col(f"q{a}") + 1), F.lit(2 * q).cast("long"))) for a in range(d)})
    names = [f"x{a}" for a in range(d)]
    inv = F.pow(F.col("side") / F.lit(float(q)) / spacing.column(names), F.lit(float(d)))
    value = F.when(domain.column(names), inv).otherwise(0.0) if domain is not None else inv
    return rows.groupBy("cell", "level").agg((F.lit(DENSITY.get(d, 0.7)) * F.sum(value)).alias("est"))


def build_estimated(spark, spacing, d: int, limit: int, domain=None, deepest: int | None = None, wide: bool = True) -> DataFrame:
    """Leaves from estimated counts, level by level; ``wide`` keeps cells at three spacings or more."""
    deep = min(deepest if deepest is not None else max_level(d), max_level(d))
    open_, done, level = uniform(spark, 0, d), None, 0
    while True:
        est = stored(estimate(open_, spacing, d, domain))
        fine = level < deep and (not wide or (SIDE >> (level + 1)) >= 3 * spacing.least + 6)
        need = F.col("est") > limit
        if wide and fine:
            names = [f"x{a}" for a in range(d)]
            mid = with_boxes(est, d).withColumns({n: F.col(f"lo{a}") + F.call_function("div", F.col("side"), F.lit(2).cast("long")) for a, n in enumerate(names)})
            est = mid.withColumn("wide", F.col("side") / 2 >= 3 * spacing.column(names) + 6).select("cell", "level", "est", "wide")
            need = need & F.col("wide")
        leaves = (est.where(~need) if fine else est).select("cell", "level", "est")
        done = leaves if done is None else done.union(leaves)
        if not fine:
            return done
        more = est.where(need)
        if more.isEmpty():
            return done
        open_ = _children(more, d)
        level += 1


def neighbours(cells: DataFrame, d: int, include_self: bool = False) -> DataFrame:
    """``cell, nbr`` for every two leaves that share a vertex, whatever their levels.

    Each leaf names the cells around it on its own level; a neighbour is that cell or an ancestor of it, so an
    equi-join on keys finds all neighbours of the same or a coarser level, and its mirror the finer ones.
    """
    boxed = with_boxes(cells.select("cell", "level"), d)
    offsets = F.array(*(F.array(*(F.lit(o) for o in off)) for off in product((-1, 0, 1), repeat=d) if any(off)))
    around = boxed.select("cell", "level", *(f"c{a}" for a in range(d)), F.explode(offsets).alias("o"))
    n_side = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("level").cast("int"))
    at = [F.col(f"c{a}") + F.col("o")[a] for a in range(d)]
    inside = reduce(and_, ((x >= 0) & (x < n_side) for x in at))
    keyed = around.where(inside).select("cell", "level", cell_key(at, F.col("level"), d).alias("near"))
    up = keyed.select("cell", F.explode(F.sequence(F.lit(0), F.col("level"))).alias("k"), "near")
    up = up.select("cell", F.call_function("shiftright", F.col("near"), (F.lit(d) * F.col("k")).cast("int")).alias("nbr"))
    found = up.join(cells.select(F.col("cell").alias("nbr")), "nbr").where("cell <> nbr").select("cell", "nbr").distinct()
    # a leaf's own ancestors are never leaves, so every hit is a true neighbour
    both = found.union(found.select(F.col("nbr").alias("cell"), F.col("cell").alias("nbr"))).distinct()
    if include_self:
        both = both.union(cells.select("cell", F.col("cell").alias("nbr")))
    return both


def colours(cells: DataFrame, d: int, by_level: bool = True) -> DataFrame:
    """Phase colour: parity of the cell's coordinates and, where levels differ by one at most, parity of the level."""
    boxed = with_boxes(cells, d)
    parity = reduce(lambda p, a: F.shiftleft(p, 1).bitwiseOR(F.col(f"c{a}").bitwiseAND(F.lit(1).cast("long"))), range(d), F.lit(0).cast("long"))
    level = (F.col("level") % 2) * (1 << d) if by_level else F.lit(0)
    return boxed.withColumn("colour", (level + parity).cast("int"))


def spatial_levels(cells: DataFrame, d: int) -> DataFrame:
    """Level to which the point tree must be split before filling: one more than the deepest cell around."""
    edges = neighbours(cells, d, include_self=True)
    deep = edges.join(cells.select(F.col("cell").alias("nbr"), F.col("level").alias("l")), "nbr").groupBy("cell").agg(F.max("l").alias("l"))
    return cells.join(deep, "cell").withColumn("spatial_level", (F.col("l") + 1).cast("int")).drop("l")


def balance(cells: DataFrame, d: int, max_rounds: int = BITS) -> DataFrame:
    """Split leaves until vertex neighbours differ by one level at most."""
    cells = cells.select("cell", "level")
    for _ in range(max_rounds):
        edges = neighbours(cells, d)
        lv = cells.select(F.col("cell").alias("nbr"), F.col("level").alias("l"))
        steep = edges.join(lv, "nbr").groupBy("cell").agg(F.max("l").alias("l")).join(cells, "cell").where(F.col("l") > F.col("level") + 1).select("cell")
        steep = stored(steep)
        if steep.isEmpty():
            return cells
        split = _children(cells.join(steep, "cell", "left_semi"), d)
        cells = stored(cells.join(steep, "cell", "left_anti").union(split))
    raise RuntimeError("tree did not balance")


def check_width(cells: DataFrame, spacing, d: int) -> DataFrame:
    """Leaves narrower than three times the largest spacing near them: ``cell, side, need``.

    The spacing is read at the centre of the leaf, on its faces and corners, and at the same places of the leaves of its size around it.
    """
    names = [f"x{a}" for a in range(d)]
    half = F.call_function("div", F.col("side"), F.lit(2).cast("long"))
    shift = F.array(*(F.array(*(F.lit(o) for o in off)) for off in product((-2, -1, 0, 1, 2), repeat=d)))
    seen = with_boxes(cells, d).select("cell", "side", *(f"lo{a}" for a in range(d)), F.explode(shift).alias("o"))
    place = {n: F.greatest(F.lit(0), F.least(F.lit(SIDE - 1), F.col(f"lo{a}") + half * (F.col("o")[a] + 1))) for a, n in enumerate(names)}
    most = seen.withColumns(place).groupBy("cell", "side").agg(F.max(3 * spacing.column(names) + 6).alias("need"))
    return most.where("side < need").select("cell", "side", "need")


def points_in_cell(points: DataFrame, cell: int, level: int, names: list[str] | None = None) -> DataFrame:
    """Rows of one cell, as plain range predicates that prune files and row groups."""
    names = names or _axes(points)
    d, code = len(names), cell - (1 << (len(names) * level))
    side = SIDE >> level
    cond = F.lit(True)
    for a, n in enumerate(names):
        c = sum(((code >> (d * b + d - 1 - a)) & 1) << b for b in range(level))
        cond = cond & (F.col(n) >= c * side) & (F.col(n) < (c + 1) * side)
    return points.where(cond)


def merged_tree(work: DataFrame, points: DataFrame, d: int, leaf: int = 40) -> DataFrame:
    """Both roles in one table: point-tree leaves with the work cell above each."""
    fine = build_counted(points, leaf, names=[f"x{a}" for a in range(d)])
    up = fine.select("cell", "level", "est", F.explode(F.sequence(F.lit(0), F.col("level"))).alias("k"))
    up = up.withColumn("work_cell", F.call_function("shiftright", F.col("cell"), (F.lit(d) * F.col("k")).cast("int")))
    above = up.join(work.select(F.col("cell").alias("work_cell")).hint("merge"), "work_cell").select("cell", "work_cell")
    return fine.join(above.hint("merge"), "cell", "left")


class Leaves:
    """A linear tree for kernels: the leaf of a coordinate by one search in Morton order."""

    def __init__(self, cell: np.ndarray, level: np.ndarray, colour: np.ndarray, d: int):
        self.d, deep = d, max_level(d)
        start = (cell - (1 << (d * level.astype(np.int64)))) << (d * (deep - level.astype(np.int64)))
        order = np.argsort(start)
        self.cell, self.level, self.colour, self.start = cell[order], level[order].astype(np.int64), colour[order], start[order]
        code = self.cell - (np.int64(1) << (d * self.level))
        self.c = np.stack([sum(((code >> (d * b + d - 1 - a)) & 1) << b for b in range(deep)) for a in range(d)], axis=1)
        self.side = np.int64(SIDE) >> self.level
        self.lo = self.c * self.side[:, None]
        self.rank = np.empty(len(cell), np.int64)
        self.rank[np.lexsort([self.lo[:, a] for a in range(d - 1, -1, -1)])] = np.arange(len(cell))

    def of(self, x: np.ndarray) -> np.ndarray:
        """Index of the leaf that holds each point."""
        deep = max_level(self.d)
        clip = np.clip(x, 0, SIDE - 1)
        code = morton([clip[..., a] >> (BITS - deep) for a in range(self.d)], deep)
        return np.searchsorted(self.start, code, side="right") - 1

    @classmethod
    def uniform(cls, level: int, d: int) -> Leaves:
        n = 1 << level
        grid = np.stack(np.meshgrid(*([np.arange(n)] * d), indexing="ij"), axis=-1).reshape(-1, d)
        cell = key_array([grid[:, a] for a in range(d)], level)
        colour = np.zeros(len(cell), np.int64)
        for a in range(d):
            colour = (colour << 1) | (grid[:, a] & 1)
        return cls(cell, np.full(len(cell), level), colour, d)
