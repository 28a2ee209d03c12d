"""Spatial joins and thinning on rows of ordinary tables, by equi-joins on grid cells.

No operator here forms all pairs: a row meets only rows of the cells around its own, cells are at least as wide as the radius, and thinning
works on one row a cell and round, so a cell that holds a third of all rows costs its rows once a round.
"""

from __future__ import annotations

from functools import reduce
from itertools import product
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frontfill.functions.lattice import BITS, SIDE, cell_key, max_level, priority, squared
from frontfill.operators.tree import point_key, with_boxes
from frontfill.sources.store import stored


def _div(c: Column, n) -> Column:
    return F.call_function("div", c, F.lit(int(n)).cast("long"))


def _offsets(d: int, rings: int = 1) -> Column:
    return F.array(*(F.array(*(F.lit(o) for o in off)) for off in product(range(-rings, rings + 1), repeat=d)))


def within_pairs(a: DataFrame, b: DataFrame, names: list[str], side: int, radius: Column, keys: tuple[str, ...] = ()) -> DataFrame:
    """Rows ``a`` x ``b`` (columns prefixed ``a_``/``b_``, ``d2``) with squared distance under ``radius`` squared.

    ``radius`` is an expression over ``a_`` columns, at most ``side``.  ``a`` is copied to the cells around: let it be the smaller
    side.  ``keys`` are further equality columns.
    """
    d = len(names)
    left = a.select(*(F.col(c).alias(f"a_{c}") for c in a.columns), F.explode(_offsets(d)).alias("__o"))
    left = left.withColumns({f"__g{i}": _div(F.col(f"a_{n}"), side) + F.col("__o")[i] for i, n in enumerate(names)})
    right = b.select(*(F.col(c).alias(f"b_{c}") for c in b.columns)).withColumns({f"__r{i}": _div(F.col(f"b_{n}"), side) for i, n in enumerate(names)})
    cond = reduce(and_, (F.col(f"__g{i}") == F.col(f"__r{i}") for i in range(d)))
    for k in keys:
        cond = cond & (F.col(f"a_{k}") == F.col(f"b_{k}"))
    d2 = squared([F.col(f"a_{n}") for n in names], [F.col(f"b_{n}") for n in names])
    # shuffled sizes are compressed and hide what a broadcast would hold
    joined = left.join(right.hint("merge"), cond).withColumn("d2", d2).where(F.col("d2") < radius * radius)
    return joined.drop("__o", *(f"__g{i}" for i in range(d)), *(f"__r{i}" for i in range(d)))


def thin(rows: DataFrame, names: list[str], h: int | Column, h_most: int | None = None, group: str | None = None, rank: Column | None = None) -> DataFrame:
    """A spacing-constrained subset: a row stays iff no kept row of smaller rank lies nearer than its ``h``.

    ``rows`` has ``id`` and the axes; rank is the hashed id, then the id.  The answer is unique.  Each round looks at the first
    undecided row of each small cell; one that comes first in all cells around stays, and undecided rows near it go.  The work
    of a round is linear in the undecided rows, and ranks are random, so rounds grow with the logarithm of the rows.
    """
    d = len(names)
    fixed = not isinstance(h, Column)
    side = max(1, int(h if fixed else h_most))
    radius = F.lit(h).cast("long") if fixed else h
    r = rank if rank is not None else F.struct(priority(F.col("id")).alias("p"), F.col("id").alias("i"))
    grp = F.col(group) if group else F.lit(0)
    live = rows.where(reduce(and_, (F.col(n).isNotNull() for n in names)) & F.col("id").isNotNull()).select("id", *names, radius.alias("__h"), r.alias("__r"), grp.alias("__grp"))
    live = stored(live.withColumns({f"__g{i}": _div(F.col(n), side) for i, n in enumerate(names)}))
    cell = ["__grp", *(f"__g{i}" for i in range(d))]
    kept_all: DataFrame | None = None
    while True:
        first = live.groupBy(*cell).agg(F.min(F.struct("__r", "id", *names, "__h")).alias("m"))
        first = stored(first.select(*cell, "m.*"))
        if first.isEmpty():
            break
        around = first.select(F.col("__grp").alias("n_grp"), F.col("__r").alias("n_r"), *(F.col(f"__g{i}") for i in range(d)), F.explode(_offsets(d)).alias("__o"))
        around = around.select("n_grp", "n_r", *((F.col(f"__g{i}") + F.col("__o")[i]).alias(f"n_g{i}") for i in range(d))).groupBy("n_grp", *(f"n_g{i}" for i in range(d))).agg(F.min("n_r").alias("n_best"))
        here = F.col("__grp").eqNullSafe(F.col("n_grp")) & reduce(and_, (F.col(f"__g{i}") == F.col(f"n_g{i}") for i in range(d)))
        kept = first.join(around, here).where(F.col("__r") == F.col("n_best")).select(*first.columns)
        kept = stored(kept)
        kept_all = kept if kept_all is None else kept_all.unionByName(kept)
        near = kept.select(F.col("__grp").alias("k_grp"), F.col("id").alias("k_id"), *(F.col(n).alias(f"k_{n}") for n in names), F.explode(_offsets(d)).alias("__o"), *(F.col(f"__g{i}").alias(f"k_g{i}") for i in range(d)))
        near = near.select("k_grp", "k_id", *(f"k_{n}" for n in names), *((F.col(f"k_g{i}") + F.col("__o")[i]).alias(f"k_g{i}") for i in range(d)))
        cond = F.col("__grp").eqNullSafe(F.col("k_grp")) & reduce(and_, (F.col(f"__g{i}") == F.col(f"k_g{i}") for i in range(d)))
        hit = (squared([F.col(n) for n in names], [F.col(f"k_{n}") for n in names]) < F.col("__h") * F.col("__h")) | (F.col("id") == F.col("k_id"))
        live = stored(live.join(near, cond & hit, "left_anti"))
    if kept_all is None:
        return rows.where(F.lit(False)).select("id", *names)
    return kept_all.select("id", *names)


def around(points: DataFrame, cells: DataFrame, names: list[str], reach: int) -> DataFrame:
    """The points with ``target, lo0.., side`` of every leaf that may lie within ``reach`` of them, however small the leaves are.

    Points are gathered in grid cells at least as wide as ``reach``.  A leaf is met through the grid cell that holds it, or, where it
    is coarser, as an ancestor of one; so two equi-joins on keys find the leaves of the cells around, of any level.
    """
    d = len(names)
    level = min(max_level(d), BITS - max(0, int(reach) - 1).bit_length()) if reach < SIDE else 0
    at = [f"__at{a}" for a in range(d)]
    located = points.withColumns({c: F.shiftright(F.col(n), BITS - level) for c, n in zip(at, names, strict=True)})
    near = located.select(*at).distinct()
    for c in at:
        near = near.select("*", F.explode(F.sequence(F.col(c) - 1, F.col(c) + 1)).alias(f"near{c}")).where(F.col(f"near{c}").between(0, (1 << level) - 1))
    up = near.select(*at, F.explode(F.sequence(F.lit(0), F.lit(level))).alias("k"), cell_key([F.col(f"near{c}") for c in at], F.lit(level), d).alias("near"))
    up = up.select(*at, F.call_function("shiftright", F.col("near"), (F.lit(d) * F.col("k")).cast("int")).alias("__meet")).distinct()
    boxed = with_boxes(cells.select("cell", "level"), d)
    finer = F.greatest(F.lit(0), F.col("level") - level)
    leaf = boxed.select(F.col("cell").alias("target"), *(f"lo{a}" for a in range(d)), "side", F.call_function("shiftright", F.col("cell"), (F.lit(d) * finer).cast("int")).alias("__meet"))
    # shuffled sizes are compressed and hide what a broadcast would hold
    met = up.join(leaf.hint("merge"), "__meet").drop("__meet")
    return located.join(met.hint("merge"), at).drop(*at)


def halo(points: DataFrame, cells: DataFrame, names: list[str], gap: int) -> DataFrame:
    """``id, target``: every point with each leaf whose box is at most ``gap`` away, its own included."""
    close = reduce(and_, ((F.col(n) >= F.col(f"lo{a}") - gap) & (F.col(n) < F.col(f"lo{a}") + F.col("side") + gap) for a, n in enumerate(names)))
    return around(points, cells, names, gap).where(close).select("id", "target")


def locate(points: DataFrame, cells: DataFrame, names: list[str]) -> DataFrame:
    """Points with the leaf that holds them: one equi-join on the keys of the levels in use."""
    d = len(names)
    levels = [r["level"] for r in cells.select("level").distinct().collect()]  # at most one a level of the tree
    keyed = points.select("*", F.explode(F.array(*(cell_key([F.shiftright(F.col(n), BITS - v) for n in names], F.lit(v), d) for v in sorted(levels)))).alias("cell"))
    return keyed.join(cells.select("cell"), "cell")


def nearest_generator(points: DataFrame, generators: DataFrame, names: list[str], first_side: int = SIDE >> 5) -> DataFrame:
    """``id, gen, d2``: the nearest generator of each point, ties to the smaller id.

    A round settles the points whose best generator in the cells around is no farther than a cell's side; the side doubles
    for the rest, so each round is one equi-join and there are at most as many as levels.
    """
    d = len(names)
    gens = generators.select(F.col("id").alias("gen"), *(F.col(n).alias(f"g_{n}") for n in names))
    left = points.select("id", *names)
    out: DataFrame | None = None
    side = first_side
    while True:
        q = left.select("id", *names, F.explode(_offsets(d)).alias("__o"))
        q = q.withColumns({f"__q{i}": _div(F.col(n), side) + F.col("__o")[i] for i, n in enumerate(names)})
        g = gens.withColumns({f"__c{i}": _div(F.col(f"g_{n}"), side) for i, n in enumerate(names)})
        cond = reduce(and_, (F.col(f"__q{i}") == F.col(f"__c{i}") for i in range(d)))
        d2 = squared([F.col(n) for n in names], [F.col(f"g_{n}") for n in names])
        best = q.join(g, cond).groupBy("id").agg(F.min(F.struct(d2.alias("d2"), "gen")).alias("b")).select("id", "b.gen", "b.d2")
        wide = side >= SIDE
        best = stored(best if wide else best.where(F.col("d2") <= F.lit(side * side)))
        out = best if out is None else out.unionByName(best)
        if wide:
            return out
        left = stored(left.join(best, "id", "left_anti"))
        if left.isEmpty():
            return out
        side *= 2
