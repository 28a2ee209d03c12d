"""Accuracy and structure measures of point sets and trees."""

from __future__ import annotations

from functools import reduce
from operator import and_

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from frontfill.functions.directions import candidates
from frontfill.operators.rows import _div, within_pairs
from frontfill.operators.tree import with_boxes
from frontfill.sources.store import stored


def violations(points: DataFrame, names: list[str], side: int, order: str = "ord", radius: str = "h_parent") -> DataFrame:
    """Pairs whose later member lies nearer to the earlier one than the radius it was tested with."""
    pts = points.select(order, radius, *names)
    return within_pairs(pts, pts, names, side, F.col(f"a_{radius}")).where(F.col(f"b_{order}") < F.col(f"a_{order}"))


def outside(points: DataFrame, domain, names: list[str]) -> DataFrame:
    return points.where(~domain.column(names))


def open_candidates(points: DataFrame, domain, d: int, side: int, k: int | None = None) -> DataFrame:
    """Candidates of all points that are inside and that nothing blocks; an exhausted fill has none."""
    names = [f"x{a}" for a in range(d)]
    cand = candidates(points.select(*names, "h"), d, k)
    cand = cand.select("h", "k", *(F.col(f"x{a}").alias(f"p{a}") for a in range(d)), *(F.col(f"c{a}").alias(f"x{a}") for a in range(d))).where(domain.column(names))
    grid = points.select(*(F.col(n).alias(f"q_{n}") for n in names))
    from frontfill.functions.lattice import squared
    from frontfill.operators.rows import _offsets

    spread = grid.select("*", F.explode(_offsets(d)).alias("o")).withColumns({f"g{i}": _div(F.col(f"q_{n}"), side) + F.col("o")[i] for i, n in enumerate(names)})
    here = cand.withColumns({f"c{i}": _div(F.col(n), side) for i, n in enumerate(names)})
    cond = reduce(and_, (F.col(f"c{i}") == F.col(f"g{i}") for i in range(d)))
    near = squared([F.col(n) for n in names], [F.col(f"q_{n}") for n in names]) < F.col("h") * F.col("h")
    # shuffled sizes are compressed and hide what a broadcast would hold
    return here.join(spread.hint("merge"), cond & near, "left_anti")


def nearest(points: DataFrame, names: list[str], reach: int) -> DataFrame:
    """``id, d2``: squared distance to the nearest other row nearer than ``reach`` (null: none).

    Rows of one place are folded into it; with another id there the distance is nought.  The other places search cells that hold few places, and
    those that find nothing nearer than a cell's side search cells twice as wide, up to ``reach``.
    """
    pts = points.select("id", *names)
    real = reduce(and_, (F.col(n).isNotNull() for n in ("id", *names)))
    sites = stored(pts.where(real).groupBy(*names).agg(F.min("id").alias("id"), F.max("id").alias("last")))
    found = [pts.where(real).join(sites.where("id <> last").select(*names), names, "left_semi").select("id", F.lit(0).cast("long").alias("d2"))] if reach > 0 else []
    side = _crowded_side(sites, names, reach)
    left = sites.where("id = last").select("id", *names)
    while reach > 0:
        near = within_pairs(left, sites, names, side, F.lit(side).cast("long")).where("not (b_id = a_id and b_last = a_id)")
        got = stored(near.groupBy(F.col("a_id").alias("id"), *(F.col(f"a_{n}").alias(n) for n in names)).agg(F.min("d2").alias("d2")))
        found.append(got.select("id", "d2"))
        if side >= reach:
            break
        left = stored(left.join(got.hint("merge"), ["id", *names], "left_anti"))
        if left.isEmpty():
            break
        side = min(2 * side, reach)
    if not found:
        return pts.select("id", F.lit(None).cast("long").alias("d2"))
    best = reduce(DataFrame.unionByName, found).groupBy("id").agg(F.min("d2").alias("d2"))
    return pts.select("id").join(best.hint("merge"), "id", "left")


def _crowded_side(sites: DataFrame, names: list[str], reach: int, most: int = 64) -> int:
    """The widest of ``reach`` and its halves whose cells hold at most ``most`` different places."""
    side = max(1, reach)
    while side > 1:
        n = sites.groupBy(*(_div(F.col(n), side) for n in names)).count().agg(F.max("count")).first()[0] or 0
        if n <= most:
            break
        # a cell's half holds a fourth in the plane, if it is not crowded itself
        side = max(1, side >> max(1, int(np.log2(n / most) / len(names))))
    return side


def regularity(points: DataFrame, names: list[str], h: int) -> DataFrame:
    """Mean, spread and quartiles of nearest-neighbour distance over spacing, on points with a neighbour within twice the spacing."""
    x = nearest(points, names, 2 * h).where("d2 is not null").withColumn("r", F.sqrt("d2") / F.lit(float(h)))
    return x.agg(F.count("*").alias("n"), F.avg("r").alias("mean"), F.stddev_pop("r").alias("spread"), F.expr("percentile(r, array(0.0, 0.25, 0.5, 0.75, 1.0))").alias("quartiles"))


def coverage(points: DataFrame, probes: DataFrame, names: list[str], reach: int) -> DataFrame:
    """``probes, covered, worst_d2``: probe sites with a point nearer than ``reach``, and the farthest such nearest point."""
    p, q = probes.select("id", *names), points.select(*names)
    best = within_pairs(p, q, names, reach, F.lit(reach).cast("long")).groupBy("a_id").agg(F.min("d2").alias("d2"))
    total = p.agg(F.count("*").alias("probes"))
    return total.crossJoin(best.agg(F.count("*").alias("covered"), F.max("d2").alias("worst_d2")))


def occupancy(located: DataFrame, cells: DataFrame, limit: int, d: int) -> DataFrame:
    """Points a leaf: fewest, mean, most, and leaves over the limit or under its ``2^d``-th part."""
    n = cells.select("cell").join(located.groupBy("cell").agg(F.count("*").alias("n")), "cell", "left").select("cell", F.coalesce("n", F.lit(0)).alias("n"))
    return n.agg(F.count("*").alias("cells"), F.min("n").alias("fewest"), F.sum("n").alias("points"), F.max("n").alias("most"), F.sum((F.col("n") > limit).cast("long")).alias("over"), F.sum((F.col("n") * (1 << d) < limit).cast("long")).alias("under"))


def tree_stats(cells: DataFrame, edges: DataFrame) -> DataFrame:
    """Leaves and neighbour links by level."""
    deg = edges.groupBy("cell").agg(F.count("*").alias("deg"))
    return cells.join(deg, "cell", "left").groupBy("level").agg(F.count("*").alias("cells"), F.sum(F.coalesce("deg", F.lit(0))).cast("long").alias("links"), F.max(F.coalesce("deg", F.lit(0))).cast("long").alias("most_links"))


def claim_degree(edges: DataFrame) -> DataFrame:
    """Neighbours examined by a claim: how many cells have how many."""
    return edges.groupBy("cell").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("cells"))


def completeness(located: DataFrame, cells: DataFrame, d: int) -> DataFrame:
    """Points held against points expected, rolled up from the leaves over every level of the tree: ``node, level, n, est``."""
    n = located.groupBy("cell").agg(F.count("*").alias("n"))
    leaf = cells.select("cell", "level", "est").join(n, "cell", "left")
    up = leaf.select(F.explode(F.sequence(F.lit(0), F.col("level"))).alias("k"), "cell", "level", F.coalesce("n", F.lit(0)).alias("n"), "est")
    return up.groupBy(F.call_function("shiftright", F.col("cell"), (F.lit(d) * F.col("k")).cast("int")).alias("node"), (F.col("level") - F.col("k")).cast("int").alias("level")).agg(F.sum("n").cast("long").alias("n"), F.sum("est").cast("long").alias("est"))


def distinct_trees(trees: list[tuple[int, DataFrame]]) -> DataFrame:
    """For each limit a fingerprint of its leaves; limits with one fingerprint build one tree."""
    rows = reduce(lambda a, b: a.unionByName(b), (t.select(F.lit(limit).cast("long").alias("limit"), "cell") for limit, t in trees))
    return rows.groupBy("limit").agg(F.count("*").alias("cells"), F.sum(F.pmod(F.col("cell") * 48271 + 11, F.lit(2147483647))).cast("long").alias("print")).withColumn("same_as", F.min("limit").over(Window.partitionBy("cells", "print")))


def separation(vectors: DataFrame, tau: float, most: int = 16_384) -> DataFrame:
    """Pairs of vectors of one length nearer than ``tau``, by exact distance: ``a, b, dist`` with ``a < b``.

    High dimension has no useful grid, so all pairs meet, as products of blocks of at most about ``most`` rows, two blocks a task.  A product
    only proposes: what it does not rule out with room for rounding is decided by the sum of squares, component by component.
    Rows without an id, a vector or one of its components have no pairs.
    """
    whole = F.col("id").isNotNull() & F.col("vec").isNotNull() & ~F.exists("vec", lambda x: x.isNull())
    v = stored(vectors.where(whole).select("id", F.col("vec").cast("array<double>").alias("vec"), F.monotonically_increasing_id().alias("row")))
    n = v.count()
    blocks = max(1, -(-n // most), min(8, -(-n // 256)))
    dealt = v.select("id", "vec", (F.col("row") % blocks).alias("block"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("other"))
    lo, hi = F.least("block", "other"), F.greatest("block", "other")
    # two blocks' place among all unordered ones
    unit = lo * blocks - F.call_function("div", lo * (lo - 1), F.lit(2).cast("long")) + hi - lo
    units = blocks * (blocks + 1) // 2
    dealt = dealt.select("id", "vec", "block", (F.col("block") == F.col("other")).alias("alone"), unit.cast("int").alias("unit"))

    def meet(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        ids, block, alone = t["id"].to_numpy(), t["block"].to_numpy(), bool(t["alone"][0].as_py())
        vec = t["vec"].combine_chunks()
        size = pa.compute.list_value_length(vec).to_numpy(zero_copy_only=False)
        begin = np.cumsum(size) - size
        flat = vec.flatten().to_numpy(zero_copy_only=False)
        for d in np.unique(size).tolist():
            mine = np.flatnonzero(size == d)
            x = flat[begin[mine][:, None] + np.arange(d)]
            p = np.arange(len(mine)) if alone else np.flatnonzero(block[mine] == block[mine].min())
            q = p if alone else np.setdiff1d(np.arange(len(mine)), p)
            if not alone and len(np.unique(block[mine])) < 2:
                continue
            norm = (x * x).sum(axis=1)
            for at in range(0, len(p), 256):
                rows = p[at : at + 256]
                both = norm[rows][:, None] + norm[q][None, :]
                i, j = np.nonzero(~(both - 2 * (x[rows] @ x[q].T) > tau * tau + 1e-9 * (both + tau * tau)))
                i, j = rows[i], q[j]
                once = ids[mine[i]] < ids[mine[j]] if alone else ids[mine[i]] != ids[mine[j]]
                i, j = i[once], j[once]
                for k in range(0, len(i), 100_000):
                    a, b = i[k : k + 100_000], j[k : k + 100_000]
                    total = np.zeros(len(a))
                    for c in range(d):
                        total += (x[a, c] - x[b, c]) ** 2
                    dist = np.sqrt(total)
                    near = dist < tau
                    first, second = ids[mine[a[near]]], ids[mine[b[near]]]
                    yield pa.RecordBatch.from_pydict({"a": pa.array(np.minimum(first, second), pa.int64()), "b": pa.array(np.maximum(first, second), pa.int64()), "dist": pa.array(dist[near], pa.float64())})

    return dealt.repartitionById(units, F.col("unit")).mapInArrow(meet, "a long, b long, dist double")


def boxes(cells: DataFrame, d: int) -> DataFrame:
    return with_boxes(cells, d)
