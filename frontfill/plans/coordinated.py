"""Distributed-memory mode, proximity repair, and refilling after the spacing changes.

In the coordinated mode every worker fills on its own points.  After each round the coarse cells that workers have entered are compared; a cell
entered by two goes to the one that was first (then the lower number), the points of both in it and around it are reconciled, and
what is removed reopens its surroundings.  Later rounds see the points near a worker's cells, so clashes die out; at the end the
workers' point sets are one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.functions.directions import directions
from frontfill.functions.kernel import Grid, front_fill, settle
from frontfill.functions.lattice import BITS, SIDE, cell_key, key_array
from frontfill.operators.rows import within_pairs
from frontfill.plans import seams
from frontfill.sources.store import stored

LOCAL = "worker long, round long, seq long, h_parent long, open boolean"


def repair(points: DataFrame, names: list[str], order: list[str], side: int, radius: str = "h_parent") -> tuple[DataFrame, DataFrame]:
    """(kept, removed): drop the later point of each violating pair, in order, so that no violation is left.

    ``order`` are columns that rank the points; a point goes iff a kept point of smaller rank lies nearer than its ``radius``.
    """
    # the axes and the rank identify a point: accepted points never coincide
    named = stored(points.withColumns({"id": F.xxhash64(*names, *order), "rank": F.struct(*(F.col(c) for c in order))}))
    slim = named.select("id", "rank", F.col(radius).alias("r"), *names)
    pairs = within_pairs(slim, slim, names, side, F.col("a_r")).where("b_rank < a_rank")
    live = stored(pairs.select(F.col("a_id").alias("late"), F.col("b_id").alias("early")))
    gone: DataFrame | None = None
    while not live.isEmpty():
        # a point whose earlier rivals are all settled as removed is kept; so is one that never comes late
        kept = live.select(F.col("early").alias("k")).distinct().join(live.select(F.col("late").alias("k")).distinct(), "k", "left_anti")
        out = stored(live.join(kept, F.col("early") == F.col("k"), "left_semi").select(F.col("late").alias("id")).distinct())
        gone = out if gone is None else gone.unionByName(out)
        live = live.join(out, F.col("late") == F.col("id"), "left_anti")
        live = stored(live.join(out, F.col("early") == F.col("id"), "left_anti"))
    named = named.drop("rank")
    if gone is None:
        return named.drop("id"), named.where(F.lit(False)).drop("id")
    return named.join(gone, "id", "left_anti").drop("id"), named.join(gone, "id", "left_semi").drop("id")


def reopen(points: DataFrame, removed: DataFrame, names: list[str], reach: int) -> DataFrame:
    """``points`` with ``open`` set on those within ``reach`` of a removed one."""
    named = points.withColumn("id", F.xxhash64(*names))
    near = within_pairs(removed.select(*names), named.select("id", *names), names, reach, F.lit(reach).cast("long")).select(F.col("b_id").alias("id")).distinct().withColumn("hit", F.lit(True))
    return named.join(near, "id", "left").withColumn("open", F.col("open") | F.coalesce("hit", F.lit(False))).drop("id", "hit")


def fill_coordinated(spark, domain, spacing, seeds: np.ndarray, coarse_level: int = 3, quantum: int = 200, d: int = 2, k: int | None = None, patience: int = 12) -> DataFrame:
    """``x0.., worker, round, seq, h_parent, open``: one worker a seed; ``open`` is false everywhere when done.

    Rounds go on while points are added; the quantum grows with them, so their number grows with the logarithm of the fill.  ``patience`` rounds
    without more points raise.  Only points in coarse cells that border on another worker's are compared between workers.
    """
    names = [f"x{a}" for a in range(d)]
    dirs = directions(d, k)
    schema = ", ".join(f"{n} long" for n in names) + ", " + LOCAL
    h = spacing.most
    pts = stored(spark.createDataFrame([(*map(int, s), w, 0, 0, int(spacing.at(np.array([s]))[0]), True) for w, s in enumerate(seeds)], schema))
    here = cell_key([F.shiftright(F.col(n), BITS - coarse_level) for n in names], F.lit(coarse_level), d)
    rnd = most = idle = 0
    rings = -(-4 * h // (SIDE >> coarse_level))
    while True:
        rnd += 1
        quantum = quantum * 5 // 4 if rnd > 1 else quantum
        # a cell belongs to who entered it first
        owner = stored(pts.groupBy(here.alias("cell")).agg(F.min(F.struct("round", "worker")).alias("o")).select("cell", F.col("o.worker").alias("owner")))
        placed = pts.withColumn("cell", here).join(owner, "cell").drop("worker").withColumnRenamed("owner", "worker")
        pts = stored(placed.select(*names, *(c.split()[0] for c in LOCAL.split(", "))))
        if pts.where("open").isEmpty():
            return pts
        n = pts.count()
        idle, most = (0, n) if n > most else (idle + 1, most)
        if idle > patience:
            raise RuntimeError("coordinated fill did not finish")
        # a row a coarse cell at most, a number that the level fixes and the data does not
        held = {r["cell"]: r["owner"] for r in owner.collect()}
        # foreign points near a worker's own are visible, but not his to expand
        rim = border_cells(held, coarse_level, d, rings)
        close = pts.where(here.isin(rim)) if rim else pts.where(F.lit(False))
        mine = close.select("worker", *names)
        seen = within_pairs(mine, close, names, 4 * h, F.lit(4 * h).cast("long")).where("a_worker <> b_worker")
        seen = seen.select(F.col("a_worker").alias("worker"), *(F.col(f"b_{n}").alias(n) for n in names)).distinct()
        run = _local_round(names, schema, domain, spacing, dirs, coarse_level, quantum, rnd, held)
        grown = stored(pts.groupBy("worker").cogroup(seen.groupBy("worker")).applyInArrow(run, schema))
        kept, removed = repair(grown, names, ["round", "worker", "seq"], h)
        removed = stored(removed)
        pts = stored(kept if removed.isEmpty() else reopen(kept, removed, names, 2 * h + 8))


def border_cells(held: dict[int, int], level: int, d: int, rings: int = 1) -> list[int]:
    """Cells within ``rings`` of a cell of another owner."""
    keys = np.array(sorted(held), np.int64)
    code = keys - (1 << (d * level))
    at = np.stack([sum(((code >> (d * b + d - 1 - a)) & 1) << b for b in range(level)) for a in range(d)], axis=1) if level else np.zeros((len(keys), d), np.int64)
    whose = {tuple(c): held[int(k)] for c, k in zip(at.tolist(), keys, strict=True)}
    shifts = [tuple(x - rings for x in o) for o in np.ndindex(*([2 * rings + 1] * d))]
    return [int(k) for c, k in zip(at.tolist(), keys, strict=True) if any(whose.get(tuple(x + s for x, s in zip(c, o, strict=True)), held[int(k)]) != held[int(k)] for o in shifts)]


def _local_round(names, schema, domain, spacing, dirs, level, quantum, rnd, held):
    """One worker's round on its own points: expand up to ``quantum`` of them, children too where no other worker owns their cell."""
    d = len(names)
    keys = np.array(sorted(held), np.int64)
    whose = np.array([held[k] for k in sorted(held)], np.int64)

    def run(key, left, right):
        w = key[0].as_py()
        own = np.stack([left[n].to_numpy() for n in names], axis=1)
        other = np.stack([right[n].to_numpy() for n in names], axis=1)
        order = np.lexsort((left["seq"].to_numpy(), left["round"].to_numpy()))
        own = own[order]
        open_ = left["open"].to_numpy(zero_copy_only=False)[order] if len(own) else np.zeros(0, bool)
        front = np.flatnonzero(open_)
        flags = []

        def mine(child, _parent):
            cell = key_array([child[:, a] >> (BITS - level) for a in range(d)], level)
            at = np.minimum(np.searchsorted(keys, cell), len(keys) - 1)
            ok = (keys[at] != cell) | (whose[at] == w)
            flags.append(ok)
            return ok

        f = front_fill(np.concatenate([own, other]), front, spacing.at, domain.mask, dirs, spacing.most, owned=mine, limit=quantum)
        # the queue is first-in-first-out: the front went first, then owned children in order of acceptance
        still = open_.copy()
        still[front[:quantum]] = False
        n = len(f.x)
        waits = np.ones(n, bool)
        queued = np.flatnonzero(np.concatenate(flags)) if flags else np.zeros(0, np.int64)
        waits[queued[: max(0, quantum - len(front))]] = False
        cols = {nm: np.concatenate([own[:, a], f.x[:, a]]) for a, nm in enumerate(names)}
        new = {"round": np.full(n, rnd), "seq": np.arange(n), "h_parent": f.h_parent}
        cols |= {"worker": np.full(len(own) + n, w)} | {c: np.concatenate([left[c].to_numpy()[order], v]) for c, v in new.items()}
        out = {c: pa.array(cols[c], pa.int64()) for c in (*names, "worker", "round", "seq", "h_parent")}
        return pa.table({**out, "open": pa.array(np.concatenate([still, waits]))})

    return run


def _split(points: DataFrame, names: list[str], old, new, level: int) -> tuple[DataFrame, object]:
    """The points with ``same``: is the spacing at the centre of their cell unchanged; and the function that says where it is not."""
    side = 1 << (BITS - level)
    mids = {n: F.call_function("div", F.col(n), F.lit(side).cast("long")) * side + side // 2 for n in names}
    there = points.select(*names, *(m.alias(f"m_{n}") for n, m in mids.items()))
    same = old.column([f"m_{n}" for n in names]) == new.column([f"m_{n}" for n in names])

    def changed(x: np.ndarray) -> np.ndarray:
        mid = x // side * side + side // 2
        return old.at(mid) != new.at(mid)

    return there.select(*names, same.alias("same")), changed


def refill(points: DataFrame, names: list[str], domain, old, new, level: int = 4, k: int | None = None, block_points: int = 20_000) -> DataFrame:
    """Points after the spacing changed from ``old`` to ``new``: ``x0.., kept``.

    Points in cells of ``level`` whose spacing at the centre is unchanged are kept as they are, the others are deleted.  The fronts of
    all kept points fill what that opens, on either side of a changed cell's border.  Where they do not reach, places in changed cells are
    seeds, then the deleted points, so every part of the region that had points has some again; no candidate stays open.

    The work is dealt by blocks and seams (:mod:`frontfill.plans.seams`), so a spacing too wide for blocks raises; that is a matter of a few hundred points
    a region and :func:`refill_sequential` does it.
    """
    marked, changed = _split(points, names, old, new, level)
    marked = stored(marked)
    kept, gone = marked.where("same"), marked.where("not same or same is null")
    out = seams.fill_seams(points.sparkSession, domain, new, len(names), k, block_points, given=kept, tries=gone, changed=changed)
    return out.select(*names, (F.col("by_zone") == -1).alias("kept"))


def refill_sequential(points: DataFrame, names: list[str], domain, old, new, level: int = 4, k: int | None = None) -> DataFrame:
    """:func:`refill` as one front in one task, with the centres of changed cells as seeds; for any spacing, and for points that one task can hold."""
    d = len(names)
    side = 1 << (BITS - level)
    dirs = directions(d, k)

    def grow(x, front):
        return np.concatenate([x, front_fill(x, front, new.at, domain.mask, dirs, new.most).x])

    def run(batches):
        got = [b for b in batches if b.num_rows]
        x = np.concatenate([np.stack([b.column(i).to_numpy() for i in range(d)], axis=1) for b in got]) if got else np.zeros((0, d), np.int64)
        same = np.concatenate([b.column(d).to_numpy(zero_copy_only=False) for b in got]) if got else np.zeros(0, bool)
        order = np.lexsort([x[:, a] for a in range(d - 1, -1, -1)])
        x, same = x[order], same[order]
        n_kept = int(same.sum())
        mid = np.stack(np.meshgrid(*[np.arange(1 << level, dtype=np.int64)] * d, indexing="ij"), axis=-1).reshape(-1, d) * side + side // 2
        mid = mid[changed(mid)]
        full = grow(x[same], np.arange(n_kept))
        for seeds in (mid, x[~same]):
            seeds = seeds[domain.mask(seeds)]
            grid = Grid(d, new.most)
            grid.add(full, 0)
            seeds = seeds[settle(seeds, new.at(seeds), grid, full, 1)]
            full = grow(np.concatenate([full, seeds]), len(full) + np.arange(len(seeds)))
        yield pa.RecordBatch.from_pydict({**{n: pa.array(full[:, a], pa.int64()) for a, n in enumerate(names)}, "kept": pa.array(np.arange(len(full)) < n_kept)})

    marked, changed = _split(points, names, old, new, level)
    return marked.repartition(1).mapInArrow(run, ", ".join(f"{n} long" for n in names) + ", kept boolean")
