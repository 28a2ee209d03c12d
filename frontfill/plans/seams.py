"""Filling by blocks and seams: every worker at once in the first stage, the gaps between them after it.

The root cube is cut into blocks.  A *zone* of family ``p`` lies around faces of the blocks in ``p`` axes and inside a block in the others:
family 0 are the blocks without their rim, family 1 the seams between two blocks, the last one the places where corners meet.
Zones of one family are farther apart than a candidate can be from its parent, so all of them are filled at once and no task
reads what another writes.  Zones of different families overlap so far that around every place there is one zone, its *home*,
that holds all candidates of a point there.  A point is expanded once, in its home; a point that a front puts into another's
home waits there for that zone's turn.

Nearly all points come from family 0, one job without a shuffle.  The other families read the points near faces alone, a share that falls with the
size of a block, so what is shuffled grows with the seams and not with the fill.  Homes follow from coordinates: no
leaf table goes to the driver or to the workers.  A sweep over the families is a stage; stages repeat, for the zones where points wait, until none does.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations, product
from operator import and_, or_

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frontfill.functions.directions import directions
from frontfill.functions.domain import Domain
from frontfill.functions.kernel import Grid, front_fill, settle
from frontfill.functions.lattice import SIDE
from frontfill.functions.spacing import Spacing
from frontfill.operators.tree import DENSITY
from frontfill.sources.store import stored

WIDTH = 20
#: places to start from lie so many candidate radii apart: about a hundred points each in the plane
SEED_GAP = 10
#: about how many points one call of the kernel fills, and with it what a task holds at a time
CALL_POINTS = 100_000
#: about how many points a task fills before its result is written
TASK_POINTS = 1_000_000
#: stage of a row that is no point but a place to start from
TRY = -1
POINT = ("h", "h_parent", "zone", "family", "by_zone", "stage", "phase", "seq")


class Zones:
    """Blocks of one side, and the zones around their faces."""

    def __init__(self, spacing: Spacing, d: int, block_points: int):
        self.d, self.reach = d, spacing.most + 8
        # keep[p]: distance from faces that a zone of family p has in its inner axes; wide[p]: that to which it extends in the others
        self.keep, self.wide = [self.reach], [0]
        for _ in range(d):
            self.wide.append(self.keep[-1] + 2 * self.reach)
            self.keep.append(self.wide[-1] + self.reach)
        least = 2 * self.wide[-1] + 2 * self.reach + 2
        want = int(spacing.most * (block_points / DENSITY.get(d, 0.7)) ** (1 / d))
        self.count = max(1, SIDE // max(least, want, SIDE >> (WIDTH - 2)))
        self.side = -(-SIDE // self.count)
        self.rim = self.wide[-1] + self.reach
        if self.side < least:
            raise ValueError("spacing too wide for blocks; use fill_sequential")

    def _near(self, x: np.ndarray):
        """(block, nearest face, distance to it) on each axis."""
        at = np.clip(x, 0, SIDE - 1) // self.side
        off = x - at * self.side
        return at, at + (off > self.side - off), np.minimum(np.abs(off), np.abs(self.side - off))

    def _key(self, at, face, flat):
        part = np.where(flat, face * 2 + 1, at * 2)
        return reduce(lambda k, a: k | (part[:, a].astype(np.int64) << (WIDTH * a)), range(self.d), np.zeros(len(part), np.int64))

    def home(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Key and family of the zone that holds every candidate of a point there."""
        at, face, gap = self._near(x)
        rank = np.argsort(np.argsort(gap, axis=1, kind="stable"), axis=1, kind="stable")
        ordered = np.sort(gap, axis=1)
        family = np.full(len(x), self.d)
        for p in range(self.d, -1, -1):
            fits = np.ones(len(x), bool)
            if p:
                fits &= ordered[:, p - 1] <= self.wide[p] - self.reach
            if p < self.d:
                fits &= ordered[:, p] >= self.keep[p] + self.reach
            family[fits] = p
        return self._key(at, face, rank < family[:, None]), family

    def holder(self, x: np.ndarray, p: int) -> np.ndarray:
        """Key of the zone of a family that holds each point, for points that lie in one."""
        at, face, gap = self._near(x)
        return self._key(at, face, gap <= self.wide[p] if p else np.zeros(gap.shape, bool))

    def trials(self, zone: int) -> np.ndarray:
        """Places to start from in a zone: a lattice of the places whose home it is."""
        p = sum((zone >> (WIDTH * b)) & 1 for b in range(self.d))
        steps = []
        for a in range(self.d):
            part = (zone >> (WIDTH * a)) & ((1 << WIDTH) - 1)
            mid, half = ((part >> 1) * self.side, self.wide[p] - self.reach) if part & 1 else ((part >> 1) * self.side + self.side // 2, self.side // 2 - self.keep[p] - self.reach)
            # an odd number, SEED_GAP candidate radii apart or somewhat less
            n = 2 * max(1, -(-half // (SEED_GAP * self.reach))) + 1
            steps.append([mid + (2 * i - n + 1) * half // (n - 1) for i in range(n)])
        x = np.array(list(product(*steps)), np.int64)
        return x[((x >= 0) & (x < SIDE)).all(axis=1)]

    def near_keys(self, names: list[str], p: int) -> Column:
        """The zones of a family whose surroundings, as far as a candidate's radius reaches, hold a point."""
        side = F.lit(self.side)
        at = [F.call_function("div", F.col(n), side.cast("long")) for n in names]
        off = [F.col(n) - a * side for n, a in zip(names, at, strict=True)]
        gap = [F.least(o, side - o) for o in off]
        face = [a + (o > side - o).cast("long") for a, o in zip(at, off, strict=True)]
        keys = []
        for flat in combinations(range(self.d), p):
            inside = reduce(and_, (gap[a] <= self.wide[p] + self.reach if a in flat else gap[a] >= self.keep[p] - self.reach for a in range(self.d)))
            parts = [F.shiftleft(face[a] * 2 + 1 if a in flat else at[a] * 2, WIDTH * a) for a in range(self.d)]
            keys.append(F.when(inside, reduce(lambda k, q: k.bitwiseOR(q), parts)))
        return F.array_compact(F.array(*keys))

    def frame(self, spark, p: int, box: list[tuple[int, int]] | None) -> DataFrame:
        """``target``: the keys of all zones of a family that meet a box, counted out by a range."""
        out: DataFrame | None = None
        for flat in combinations(range(self.d), p):
            sizes = [self.count + (a in flat) for a in range(self.d)]
            ids, rest = [], F.col("id")
            for n in sizes:
                ids.append(F.pmod(rest, F.lit(n).cast("long")))
                rest = F.call_function("div", rest, F.lit(n).cast("long"))
            zones = spark.range(int(np.prod(sizes, dtype=object)))
            for a, (lo, hi) in enumerate(box or []):
                first = ids[a] * self.side - (self.wide[p] if a in flat else 0)
                last = ids[a] * self.side + (self.wide[p] if a in flat else self.side)
                zones = zones.where((first <= hi) & (last >= lo))
            keys = zones.select(reduce(lambda k, q: k.bitwiseOR(q), (F.shiftleft(i * 2 + int(a in flat), WIDTH * a) for a, i in enumerate(ids))).alias("target"))
            out = keys if out is None else out.unionByName(keys)
        return out


def fill_zones(
    zones: Zones, domain: Domain, spacing: Spacing, dirs: np.ndarray, mine: np.ndarray, pts: dict[str, np.ndarray], stage: int, p: int, changed=None, tries: np.ndarray | None = None
) -> dict[str, np.ndarray]:
    """Fill the given zones of family ``p`` from the points around them; returns the new points' columns.

    ``changed`` says at which places the lattice of starts may be used; ``tries`` are further places to start from, after it.
    """
    d, now = zones.d, stage * (zones.d + 1) + p
    x = pts["x"]
    born = pts["stage"] * (d + 1) + pts["phase"]
    waits = np.flatnonzero(np.isin(pts["zone"], mine) & (pts["by_zone"] != pts["zone"]) & (born > now - (d + 1)))
    waits = waits[np.lexsort((pts["seq"][waits], pts["by_zone"][waits], born[waits]))]
    added: list[np.ndarray] = []
    radii: list[np.ndarray] = []

    def grow(front: np.ndarray) -> None:
        nonlocal x
        if len(front):
            f = front_fill(x, front, spacing.at, domain.mask, dirs, spacing.most, owned=lambda child, _: zones.home(child)[1] == p)
            added.append(f.x)
            radii.append(f.h_parent)
            x = np.concatenate([x, f.x])

    def plant(seeds: np.ndarray) -> np.ndarray:
        nonlocal x
        grid = Grid(d, spacing.most)
        grid.add(x, 0)
        seeds = seeds[settle(seeds, spacing.at(seeds), grid, x, 1)]
        added.append(seeds)
        radii.append(spacing.at(seeds))
        x = np.concatenate([x, seeds])
        return len(x) - len(seeds) + np.arange(len(seeds))

    grow(waits)
    if stage == 1:
        places = np.concatenate([zones.trials(int(z)) for z in mine] or [np.zeros((0, d), np.int64)])
        ok = domain.mask(places) & (zones.home(places)[1] == p)
        if changed is not None:
            ok &= changed(places)
        # many fronts in a zone: waves are wide, and every part of the region that holds a place of the lattice is reached
        if ok.any():
            grow(plant(places[ok]))
        if tries is not None and len(tries):
            key, family = zones.home(tries)
            ok = domain.mask(tries) & (family == p) & np.isin(key, mine)
            if ok.any():
                grow(plant(tries[ok]))
    new = np.concatenate(added) if added else np.zeros((0, d), np.int64)
    zone, family = zones.home(new)
    by = zones.holder(new, p)
    order = np.argsort(by, kind="stable")
    seq = np.zeros(len(new), np.int64)
    first = np.flatnonzero(np.diff(by[order], prepend=-1))
    seq[order] = np.arange(len(new)) - np.repeat(first, np.diff(np.append(first, len(new))))
    return {
        "x": new, "h": spacing.at(new), "h_parent": np.concatenate(radii) if radii else np.zeros(0, np.int64), "zone": zone, "family": family,
        "by_zone": by, "stage": np.full(len(new), stage), "phase": np.full(len(new), p), "seq": seq,
    }


def seam_arrays(domain: Domain, spacing: Spacing, d: int = 2, k: int | None = None, block_points: int = 20_000, max_stages: int = 64) -> dict[str, np.ndarray]:
    """The whole fill in one process, all zones of a family in one call: the reference for the distributed form."""
    zones = Zones(spacing, d, block_points)
    dirs = directions(d, k)
    every = [np.array([sum((i * 2 + (a in flat)) << (WIDTH * a) for a, i in enumerate(ids)) for flat in combinations(range(d), p) for ids in product(*(range(zones.count + (a in flat)) for a in range(d)))], np.int64) for p in range(d + 1)]
    pts = {"x": np.zeros((0, d), np.int64), **{c: np.zeros(0, np.int64) for c in POINT}}
    for stage in range(1, max_stages):
        went = False
        for p in range(d + 1):
            born, now = pts["stage"] * (d + 1) + pts["phase"], stage * (d + 1) + p
            mine = every[p] if stage == 1 else np.unique(pts["zone"][(pts["family"] == p) & (pts["by_zone"] != pts["zone"]) & (born > now - (d + 1))])
            if len(mine):
                went = True
                new = fill_zones(zones, domain, spacing, dirs, mine, pts, stage, p)
                pts = {c: np.concatenate([pts[c], new[c]]) for c in pts}
        if not went:
            return pts
    raise RuntimeError("seam fill did not finish")


def by_zones(batches, most: int):
    """Tables of up to ``most`` whole zones from batches in which a zone's rows are adjacent."""
    rest: pa.Table | None = None
    for b in batches:
        if not b.num_rows:
            continue
        rest = pa.Table.from_batches([b]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([b])])
        target = rest["target"].to_numpy()
        first = np.flatnonzero(np.diff(target, prepend=target[0] - 1))
        for lo, hi in zip(first[::most], first[most::most], strict=False):
            yield rest.slice(int(lo), int(hi - lo))
        rest = rest.slice(int(first[(len(first) - 1) // most * most]))
    if rest is not None and rest.num_rows:
        yield rest


def placed(points: DataFrame, names: list[str], zones: Zones, spacing: Spacing, stage: int) -> DataFrame:
    """Points of another origin as rows of the fill, waiting for their homes."""

    def run(batches):
        for b in batches:
            x = np.stack([b.column(a).to_numpy() for a in range(len(names))], axis=1)
            h = spacing.at(x)
            zone, family = zones.home(x)
            same = {"by_zone": -1, "stage": stage, "phase": 0, "seq": 0}
            cols = {"h": h, "h_parent": h, "zone": zone, "family": family, **{c: np.full(len(x), v) for c, v in same.items()}}
            yield pa.RecordBatch.from_pydict({**{n: b.column(a) for a, n in enumerate(names)}, **{c: pa.array(np.asarray(cols[c], np.int64)) for c in POINT}})

    return points.select(*(F.col(n).cast("long") for n in names)).mapInArrow(run, ", ".join(f"{c} long" for c in (*names, *POINT)))


def fill_seams(
    spark, domain: Domain, spacing: Spacing, d: int = 2, k: int | None = None, block_points: int = 20_000, tasks: int | None = None, max_stages: int = 64,
    given: DataFrame | None = None, tries: DataFrame | None = None, changed=None,
) -> DataFrame:
    """Fill a region block by block, then the seams: ``x0.., h, h_parent, zone, family, by_zone, stage, phase, seq``.

    ``block_points`` is about how many points a whole block gets; a task works through its zones some ``CALL_POINTS`` points at a time, and that is what it holds.
    ``tasks`` is the number of tasks of the first family.

    A region that holds points already is filled up: ``given`` (``x0..``) are points that stay and whose fronts go on, in the result with ``by_zone`` -1;
    ``tries`` are places to start from where those do not reach; ``changed`` says where the lattice of starts may be used.
    """
    zones = Zones(spacing, d, block_points)
    dirs = directions(d, k)
    names = [f"x{a}" for a in range(d)]
    schema = ", ".join(f"{c} long" for c in (*names, *POINT))
    whole = zones.count**d
    tasks = tasks or min(whole, max(2 * spark.sparkContext.defaultParallelism, whole * block_points // TASK_POINTS))
    a_call = max(1, CALL_POINTS // block_points)

    def kernel(stage: int, p: int):
        def run(batches):
            for table in by_zones(batches, a_call):
                yield from fill(table)

        def fill(table):
            mine = np.unique(table["target"].to_numpy())
            real = table.filter(pa.compute.is_valid(table["x0"])) if "x0" in table.column_names else table.slice(0, 0)
            starts = np.zeros((0, d), np.int64)
            if real.num_rows:
                sought = pa.compute.equal(real["stage"], TRY)
                starts = np.unique(np.stack([c.to_numpy() for c in real.filter(sought).select(names).columns], axis=1), axis=0)
                real = real.filter(pa.compute.invert(sought))
            x = np.stack([real[n].to_numpy() for n in names], axis=1) if real.num_rows else np.zeros((0, d), np.int64)
            # a point near two zones of the call has come twice
            x, once = np.unique(x, axis=0, return_index=True) if len(x) else (x, np.zeros(0, np.int64))
            pts = {"x": x, **{c: real[c].to_numpy()[once] if len(x) else np.zeros(0, np.int64) for c in POINT}}
            new = fill_zones(zones, domain, spacing, dirs, mine, pts, stage, p, changed, starts)
            cols = {**{n: new["x"][:, a] for a, n in enumerate(names)}, **{c: new[c] for c in POINT}}
            yield from pa.table({c: pa.array(np.asarray(v), pa.int64()) for c, v in cols.items()}).to_batches(max_chunksize=1 << 17)

        return run

    # seams hold a share of the points that falls with the block's size
    few = max(spark.sparkContext.defaultParallelism, tasks // 8)
    held_before = [placed(f, names, zones, spacing, s) for f, s in ((given, 1), (tries, TRY)) if f is not None]
    blocks = zones.frame(spark, 0, domain.box())
    if held_before:
        before = stored(reduce(DataFrame.unionByName, held_before))
        blocks = before.select(*names, *POINT, F.explode(zones.near_keys(names, 0)).alias("target")).unionByName(blocks, allowMissingColumns=True).repartition(tasks, "target").sortWithinPartitions("target")
    else:
        blocks = blocks.repartition(tasks)
    inner = stored(blocks.mapInArrow(kernel(1, 0), schema))
    at = [F.pmod(F.col(n), F.lit(zones.side).cast("long")) for n in names]
    near = reduce(or_, ((o <= zones.rim) | (o >= zones.side - zones.rim) for o in at))
    parts = [before.where(F.col("stage") != TRY), inner] if held_before else [inner]
    rim = [stored(reduce(DataFrame.unionByName, parts).where(near).coalesce(few))]
    sought = [before.where(F.col("stage") == TRY)] if tries is not None else []
    clock = F.col("stage") * (d + 1) + F.col("phase")
    waiting = set(range(1, d + 1))
    for stage in range(1, max_stages):
        went = False
        for p in range(d + 1):
            # what this stage has added may wait for any family that comes after
            if p not in waiting and not went:
                continue
            source = reduce(DataFrame.unionByName, [*(rim if p else parts), *(sought if stage == 1 else [])])
            sent = source.select(*names, *POINT, F.explode(zones.near_keys(names, p)).alias("target"))
            if stage == 1:
                rows = sent.unionByName(zones.frame(spark, p, domain.box()), allowMissingColumns=True)
            else:
                held = source.where((F.col("family") == p) & (F.col("by_zone") != F.col("zone")) & (clock > stage * (d + 1) + p - (d + 1)))
                rows = sent.join(held.select(F.col("zone").alias("target")).distinct(), "target", "left_semi")
            new = stored(rows.repartition(few, "target").sortWithinPartitions("target").mapInArrow(kernel(stage, p), schema))
            if stage > 1 and new.isEmpty():
                continue
            parts.append(new)
            rim.append(new)
            went = True
        late = reduce(DataFrame.unionByName, rim[1:]).where("by_zone <> zone").where(clock > stage * (d + 1) + F.col("family"))
        # a row a family
        waiting = {r["family"] for r in late.select("family").distinct().collect()} if len(rim) > 1 else set()
        if not waiting:
            return reduce(DataFrame.unionByName, parts)
    raise RuntimeError("seam fill did not finish")
