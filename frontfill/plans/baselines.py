"""Baselines: the two-level k-d fill with region locks, per-leaf locking, and plain point generators."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.functions.directions import directions
from frontfill.functions.domain import Domain
from frontfill.functions.kernel import Grid, settle, squared_gap
from frontfill.functions.lattice import SIDE, mix
from frontfill.functions.spacing import Constant, Spacing
from frontfill.operators.rows import thin


#: points whose generators are sought in one call: each meets those of the cells around
OWNED_AT_ONCE = 50_000
#: distances of candidates and generators in one array
PAIRS_AT_ONCE = 1 << 18


def random_points(spark, domain: Domain, draws: int) -> DataFrame:
    """Uniform hashed draws that fall inside: ``id, x0, x1``."""
    p = spark.range(draws)
    pts = p.select("id", (mix(mix(F.col("id") + 17)) % SIDE).alias("x0"), (mix(mix(mix(F.col("id") + 1_000_003))) % SIDE).alias("x1"))
    return pts.where(domain.column(["x0", "x1"]))


def lattice(spark, domain: Domain, h: int, kind: str = "square") -> DataFrame:
    """All sites of a square or hexagonal lattice inside: ``x0, x1``."""
    row = h if kind == "square" else h * 866_026 // 1_000_000
    n0, n1 = -(-SIDE // h), -(-SIDE // row)
    sites = spark.range(n0 * n1).select(F.call_function("div", F.col("id"), F.lit(n1).cast("long")).alias("i"), (F.col("id") % n1).alias("j"))
    shift = F.lit(0) if kind == "square" else (F.col("j") % 2) * (h // 2)
    sites = sites.where((F.col("i") * h < SIDE) & (F.col("j") * row < SIDE))
    return sites.select((F.col("i") * h + shift).cast("long").alias("x0"), (F.col("j") * row).alias("x1")).where(domain.column(["x0", "x1"]))


def random_packing(spark, domain: Domain, h: int, darts: int) -> DataFrame:
    """Hashed darts thinned to the spacing: ``id, x0, x1``."""
    return thin(random_points(spark, domain, darts), ["x0", "x1"], h)


def relaxed(spark, domain: Domain, n: int, steps: int = 5, h: int | None = None) -> DataFrame:
    """Random points moved apart by neighbours nearer than twice the mean gap, a grid join a step: ``id, x0, x1``."""
    from frontfill.operators.rows import within_pairs
    from frontfill.sources.store import stored

    h = h or int((36e12 * 3.141592653589793 / max(1, n)) ** 0.5)
    pts = random_points(spark, domain, n)
    names = ["x0", "x1"]
    for _ in range(steps):
        near = within_pairs(pts, pts, names, 2 * h, F.lit(2 * h).cast("long")).where("a_id <> b_id")
        pull = F.lit(float(h)) / (F.sqrt("d2") + 1.0)
        force = near.groupBy(F.col("a_id").alias("id")).agg(*(F.sum((F.col(f"a_{n}") - F.col(f"b_{n}")) * pull / (F.sqrt("d2") + 1.0)).alias(f"f{n}") for n in names))
        moved = pts.join(force, "id", "left")
        for n in names:
            moved = moved.withColumn(f"m{n}", (F.col(n) + F.coalesce(F.least(F.lit(0.25), F.greatest(F.lit(-0.25), F.col(f"f{n}") * 0.1)) * h, F.lit(0.0))).cast("long"))
        inside = domain.column(["mx0", "mx1"])
        pts = stored(moved.select("id", *(F.when(inside, F.col(f"m{n}")).otherwise(F.col(n)).alias(n) for n in names)))
    return pts


def leaf_lock_counts(points: DataFrame, cells: DataFrame, names: list[str], h: int) -> DataFrame:
    """Locks of a fill in one shared tree with a lock a leaf: one exclusive for each insert, one shared for every leaf its search ball meets."""
    from functools import reduce

    from frontfill.operators.rows import around

    gap = [F.greatest(F.lit(0), F.col(f"lo{a}") - F.col(n), F.col(n) - (F.col(f"lo{a}") + F.col("side") - 1)) for a, n in enumerate(names)]
    d2 = reduce(lambda a, b: a + b, (g * g for g in gap))
    met = around(points, cells, names, h).where(d2 < F.lit(h * h))
    return met.agg(F.countDistinct("id").alias("exclusive"), F.count("*").alias("shared"))


def voronoi_kd_arrays(domain: Domain, spacing: Spacing, generators: np.ndarray, k: int | None = None, max_rounds: int = 10_000) -> dict[str, np.ndarray | int]:
    """The two-level index fill in bulk-synchronous rounds.

    A point belongs to the region of its nearest generator.  Each round every region expands its waiting points against the state of
    the round before; points that leave a region are handed to their owner, and clashes between regions go to the lower region.
    An insert takes its region's write lock once; a search takes a read lock in each region that its ball meets.
    """
    d = generators.shape[1]
    dirs = directions(d, k)
    from frontfill.functions.directions import propose

    # generators lie about one coarse spacing apart, so two rings of twice that hold the nearest two of any inside point
    gap2 = ((generators[:, None] - generators[None, :64]) ** 2).sum(axis=2).astype(float)
    gap2[gap2 == 0] = np.inf
    wide = int(2 * np.sqrt(gap2.min())) if len(generators) > 1 else 1 << 24
    near_gen = Grid(d, max(1, wide))
    near_gen.add(generators, 0)
    bits = max(1, int(len(generators)).bit_length())

    top = np.iinfo(np.int64).max

    def met(x):
        """Generators in the cells around some points: (point, squared distance and generator in one number, so that minima carry their owner)."""
        q, g = near_gen.near(x, 1)
        return q, (squared_gap(x, q, generators, g) << bits) | g

    def least_two(n, q, key):
        """Of each of ``n`` points the two least numbers; the pairs of a point stand together in a few runs, in any order."""
        one, two = np.full(n, top), np.full(n, top)
        if len(q):
            first = np.flatnonzero(np.diff(q, prepend=-1))
            least = np.minimum.reduceat(key, first)
            rest = np.minimum.reduceat(np.where(key == np.repeat(least, np.diff(first, append=len(q))), top, key), first)
            at, of = np.concatenate([least, rest]), np.tile(q[first], 2)
            by = np.lexsort((at, of))
            at, of = at[by], of[by]
            head = np.flatnonzero(np.diff(of, prepend=-1))
            # a run has two numbers, so the one after a point's first is its second
            one[of[head]], two[of[head]] = at[head], at[head + 1]
        return one, two

    def owner_dist(x):
        """Nearest generator of each point, and the squared distances to it and to the next; some points at a time."""
        parts = [owner_some(x[at : at + OWNED_AT_ONCE]) for at in range(0, len(x), OWNED_AT_ONCE)] or [owner_some(x)]
        return tuple(np.concatenate(c) for c in zip(*parts, strict=True))

    def owner_some(x):
        one, two = least_two(len(x), *met(x))
        best, near = one & ((1 << bits) - 1), one >> bits
        second = two >> bits
        lost = np.flatnonzero(one == top)
        for i in lost.tolist():
            every = ((generators - x[i]) ** 2).sum(axis=1)
            best[i], near[i] = int(every.argmin()), int(every.min())
        return best, near, second

    def owner_around(px, cand):
        """The same for the candidates ``cand`` (n, k, d) of each of the points ``px``: those of a point choose among its generators.

        The two nearest of a candidate are no farther from its parent than the parent's second nearest and twice the way between them.
        """
        n, kk = cand.shape[:2]
        out = np.empty((3, n, kk), np.int64)
        q, key = met(px)
        two = least_two(n, q, key)[1] >> bits
        reach = np.sqrt(two.astype(float)) + 2 * np.sqrt(((cand - px[:, None]) ** 2).sum(axis=2).max(axis=1).astype(float)) + 1
        # the cells around hold all generators within a cell's side
        known = reach <= near_gen.side
        left = np.flatnonzero(~known)
        if len(left):
            for o, v in zip(out, owner_dist(cand[left].reshape(-1, d)), strict=True):
                o[left] = v.reshape(len(left), kk)
        keep = known[q] & ((key >> bits) <= (reach**2)[q])
        q, g = q[keep], (key & ((1 << bits) - 1))[keep]
        by = np.argsort(q, kind="stable")
        q, g = q[by], g[by]
        which, first, many = np.unique(q, return_index=True, return_counts=True)
        # points with equally many generators at a time, so that none are made up
        for m in np.unique(many).tolist():
            alike = np.flatnonzero(many == m)
            step = max(1, PAIRS_AT_ONCE // (kk * m))
            for at in range(0, len(alike), step):
                some = alike[at : at + step]
                mine = g[first[some][:, None] + np.arange(m)]
                p = which[some]
                key = np.zeros((len(p), kk, m), np.int64)
                for a in range(d):
                    key += (cand[p, :, a, None] - generators[mine, a][:, None]) ** 2
                key = (key << bits) | mine[:, None]
                key.partition(1, axis=2)
                out[0, p], out[1, p], out[2, p] = key[:, :, 0] & ((1 << bits) - 1), key[:, :, 0] >> bits, key[:, :, 1] >> bits
        return out

    x = generators[domain.mask(generators)]
    grid = Grid(d, spacing.most)
    grid.add(x, 0)
    region = owner_dist(x)[0]
    front = np.arange(len(x))
    writes, reads, rounds = len(x), 0, 0
    n = len(x)
    pts, regions = x, region
    while len(front) and rounds < max_rounds:
        rounds += 1
        order = np.lexsort((front, regions[front]))
        now = front[order]
        start = n
        # a round in order: what comes later meets what came before, wherever it is cut
        for cut in range(0, len(now), OWNED_AT_ONCE):
            px = pts[now[cut : cut + OWNED_AT_ONCE]]
            ph = spacing.at(px)
            cand = propose(px, ph, dirs)
            kk = cand.shape[1]
            own, near, second = owner_around(px, cand).reshape(3, -1)
            cand, radius = cand.reshape(-1, d), np.repeat(ph, kk)
            inn = domain.mask(cand)
            cand, radius, own, near, second = cand[inn], radius[inn], own[inn], near[inn], second[inn]
            # the ball meets another region where the bisector is nearer than its radius
            gap = (np.sqrt(second.astype(float)) - np.sqrt(near.astype(float))) / 2
            reads += len(cand) + int((gap < radius).sum())
            ok = settle(cand, radius, grid, pts, 1)
            new = cand[ok]
            m = len(new)
            if n + m > len(pts):
                more = max(n + m, 2 * len(pts)) - len(pts)
                pts = np.concatenate([pts, np.zeros((more, d), np.int64)])
                regions = np.concatenate([regions, np.zeros(more, np.int64)])
            grid.add(new, n)
            pts[n : n + m], regions[n : n + m] = new, own[ok]
            n += m
        writes += n - start
        front = np.arange(start, n)
    if len(front):
        raise RuntimeError("region-locked fill did not finish")
    return {"x": pts[:n], "region": regions[:n], "writes": writes, "reads": reads, "rounds": rounds}


def _coarse_and_fill(domain: Domain, spacing: Spacing, coarse_factor: int, d: int, start) -> dict[str, np.ndarray | int]:
    """The baseline with generators from a coarse fill."""
    from frontfill.functions.kernel import front_fill
    from frontfill.functions.lattice import CENTRE

    at = np.array([start or (CENTRE,) * d], np.int64)
    coarse = Constant(spacing.most * coarse_factor)
    f = front_fill(at, np.arange(1), coarse.at, domain.mask, directions(d), coarse.h)
    return voronoi_kd_arrays(domain, spacing, np.concatenate([at, f.x]))


def voronoi_kd_fill(spark, domain: Domain, spacing: Spacing, coarse_factor: int = 8, d: int = 2, start=None) -> DataFrame:
    """The measured baseline as one task: ``seq, x0.., region``; generators come from a coarse fill."""
    import pyarrow as pa

    def run(batches):
        for _ in batches:
            pass
        out = _coarse_and_fill(domain, spacing, coarse_factor, d, start)
        x = out["x"]
        yield pa.RecordBatch.from_pydict({"seq": pa.array(np.arange(len(x)), pa.int64()), **{f"x{a}": pa.array(x[:, a], pa.int64()) for a in range(d)}, "region": pa.array(out["region"], pa.int64())})

    return spark.range(1).repartition(1).mapInArrow(run, "seq long, " + ", ".join(f"x{a} long" for a in range(d)) + ", region long")


def voronoi_kd_locks(spark, domain: Domain, spacing: Spacing, coarse_factor: int = 8, d: int = 2, start=None) -> DataFrame:
    """Points, write and read locks of that fill, counted in its task: ``n, writes, reads``."""
    import pyarrow as pa

    def run(batches):
        for _ in batches:
            pass
        out = _coarse_and_fill(domain, spacing, coarse_factor, d, start)
        yield pa.RecordBatch.from_pydict({"n": pa.array([len(out["x"])], pa.int64()), "writes": pa.array([int(out["writes"])], pa.int64()), "reads": pa.array([int(out["reads"])], pa.int64())})

    return spark.range(1).repartition(1).mapInArrow(run, "n long, writes long, reads long")
