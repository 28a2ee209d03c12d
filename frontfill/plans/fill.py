"""Fills: sequential, phase-coloured, and what starts them.

``fill_phased`` is the engine's default.  Work cells of one colour are never neighbours and at least three spacings wide, so all of
them are filled at once from the points of the phases before plus a halo of two spacings; points may land up to one spacing
outside a cell, where they wait unexpanded for their own cell's turn.  A sweep over the colours is a stage; stages repeat while
any point waits.  No task reads what another writes, so the result is that of one kernel visiting the cells in order,
whatever the number of tasks, and a lost task is simply run again.
"""

from __future__ import annotations

import math
from functools import reduce
from itertools import product
from operator import and_

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.functions.directions import directions
from frontfill.functions.domain import Domain
from frontfill.functions.kernel import Grid, front_fill, settle
from frontfill.functions.lattice import SIDE
from frontfill.functions.spacing import Spacing
from frontfill.operators.tree import DENSITY, Leaves, colours, neighbours, uniform, uniform_level
from frontfill.sources.store import stored

#: a single-task fill is refused beyond this estimate
ONE_TASK = 50_000_000


def expected_points(domain: Domain, spacing: Spacing, d: int) -> float:
    """Coarse estimate from the bounding box and the least spacing."""
    box = domain.box() or [(0, SIDE)] * d
    vol = 1.0
    for lo, hi in box:
        vol *= max(1, hi - lo)
    return DENSITY.get(d, 0.7) * vol / float(spacing.least) ** d


def thin_seeds(x: np.ndarray, h: np.ndarray, inside: np.ndarray, side: int) -> np.ndarray:
    """Seeds that are inside and obey the spacing among themselves, in order."""
    x, h = x[inside], h[inside]
    if not len(x):
        return x
    grid = Grid(x.shape[1], side)
    return x[settle(x, h, grid, x, 1)]


def fill_sequential(
    spark,
    domain: Domain,
    spacing: Spacing,
    seeds: DataFrame,
    d: int = 2,
    k: int | None = None,
    annulus: bool = False,
    order: str = "fifo",
    limit: int | None = None,
) -> DataFrame:
    """One queue, one task: ``seq, x0.., h, h_parent, parent``.  ``seeds`` has ``ord, x0..``."""
    if expected_points(domain, spacing, d) > ONE_TASK:
        raise ValueError("too many points for one task; use fill_phased")
    dirs = directions(d, k)
    names = [f"x{a}" for a in range(d)]

    def run(batches):
        got = [b for b in batches if b.num_rows]
        x = np.concatenate([np.stack([b.column(b.schema.get_field_index(n)).to_numpy() for n in names], axis=1) for b in got]) if got else np.zeros((0, d), np.int64)
        x = thin_seeds(x, spacing.at(x), domain.mask(x), spacing.most) if len(x) else x
        f = front_fill(x, np.arange(len(x)), spacing.at, domain.mask, dirs, spacing.most, annulus=annulus, order=order, limit=limit)
        full = np.concatenate([x, f.x])
        n0 = len(x)
        cols = {"seq": np.arange(len(full)), **{n: full[:, a] for a, n in enumerate(names)}, "h": np.concatenate([spacing.at(x), f.h]), "h_parent": np.concatenate([spacing.at(x), f.h_parent]), "parent": np.concatenate([np.full(n0, -1), f.parent])}
        yield pa.RecordBatch.from_pydict({c: pa.array(v, pa.int64()) for c, v in cols.items()})

    schema = "seq long, " + ", ".join(f"{n} long" for n in names) + ", h long, h_parent long, parent long"
    return seeds.select("ord", *names).repartition(1).sortWithinPartitions("ord").mapInArrow(run, schema)


def seeds_frame(spark, points, d: int = 2) -> DataFrame:
    """``ord, x0..`` of a short list of coordinates."""
    schema = "ord long, " + ", ".join(f"x{a} long" for a in range(d))
    return spark.createDataFrame([(i, *(int(v) for v in p)) for i, p in enumerate(points)], schema)


def seeds_relaxed(domain: Domain, n: int, d: int = 2, steps: int = 50, power: int = 2, seed: int = 1) -> np.ndarray:
    """``n`` points inside, spread by a repulsive radial potential among themselves and held off the border.

    The number is exact and small (one a worker), so this is a driver-side array computation.
    """
    rng = np.random.default_rng(seed)
    box = np.array(domain.box() or [(0, SIDE)] * d, np.float64)
    x = np.zeros((0, d))
    while len(x) < n:
        c = rng.uniform(box[:, 0], box[:, 1], (4 * n, d))
        x = np.concatenate([x, c[domain.mask(np.rint(c).astype(np.int64))]])[:n]
    reach = float(np.prod(box[:, 1] - box[:, 0]) / n) ** (1 / d)
    for t in range(steps):
        gap = x[:, None, :] - x[None, :, :]
        dist = np.sqrt((gap**2).sum(axis=2)) + np.eye(n) * 1e18 + 1.0
        force = (gap / dist[..., None] * (reach / dist[..., None]) ** power).sum(axis=1)
        size = np.maximum(1.0, np.sqrt((force**2).sum(axis=1, keepdims=True)))
        move = force / size * reach * 0.25 * (1 - t / steps)
        for shrink in (1.0, 0.5, 0.25):
            to = x + move * shrink
            # the border repels: a step that would come within half the reach of leaving is not made
            ok = domain.mask(np.rint(to + move / np.maximum(1.0, np.abs(move).max()) * reach * 0.5).astype(np.int64)) & domain.mask(np.rint(to).astype(np.int64))
            x = np.where(ok[:, None], to, x)
            move = np.where(ok[:, None], 0.0, move)
    return np.rint(x).astype(np.int64)


def seeds_boundary(centre: tuple[int, int], radius: int, h: int) -> list[tuple[int, int]]:
    """Points on a circle about ``h`` apart: integer rotations of a rational direction table."""
    n = max(1, int(6.283185307179586 * radius / h))
    return [(centre[0] + round(radius * np.cos(2 * np.pi * i / n)), centre[1] + round(radius * np.sin(2 * np.pi * i / n))) for i in range(n)]


def seeds_polygon(corners, h: int) -> list[tuple[int, int]]:
    """Points along the edges of a polygon, corners included, at least about ``h`` apart on each edge."""
    out = []
    for (x0, y0), (x1, y1) in zip(corners, [*corners[1:], corners[0]], strict=True):
        n = max(1, math.isqrt((x1 - x0) ** 2 + (y1 - y0) ** 2) // h)
        out += [(x0 + (x1 - x0) * i // n, y0 + (y1 - y0) * i // n) for i in range(n)]
    return out


def seeds_box(lo: tuple[int, ...], hi: tuple[int, ...], h: int) -> list[tuple[int, ...]]:
    """Points on all faces of a box, on a lattice of steps of at least about ``h``."""
    axes = []
    for a, b in zip(lo, hi, strict=True):
        n = max(1, (b - a) // h)
        axes.append([a + (b - a) * i // n for i in range(n + 1)])
    return [p for p in product(*axes) if any(v in (a, b) for v, a, b in zip(p, lo, hi, strict=True))]


def seeds_coarse(spark, domain: Domain, spacing: Spacing, start: DataFrame, factor: int, d: int = 2) -> DataFrame:
    """Seeds from a fill with ``factor`` times the spacing."""
    from frontfill.functions.spacing import Constant

    return fill_sequential(spark, domain, Constant(spacing.most * factor), start, d).select(F.col("seq").alias("ord"), *(f"x{a}" for a in range(d)))


def seeds_per_cell(cells: DataFrame, domain: Domain, d: int = 2) -> DataFrame:
    """The centre of each work cell that lies in the region: ``cell, x0..``."""
    from frontfill.operators.tree import with_boxes

    names = [f"x{a}" for a in range(d)]
    half = F.call_function("div", F.col("side"), F.lit(2).cast("long"))
    mid = with_boxes(cells.select("cell", "level"), d).select("cell", *((F.col(f"lo{a}") + half).alias(n) for a, n in enumerate(names)))
    return mid.where(domain.column(names))


POINT = ("h", "h_parent", "cell", "by_cell", "stage", "phase", "seq", "rank")


def point_schema(d: int) -> str:
    return ", ".join(f"x{a} long" for a in range(d)) + ", " + ", ".join(f"{c} long" for c in POINT)


def phase_cells(leaves: Leaves, active: np.ndarray, pts: dict[str, np.ndarray], stage: int, phase: int, domain: Domain, spacing: Spacing, dirs: np.ndarray, seed_cells: bool) -> dict[str, np.ndarray]:
    """Fill the given non-adjacent leaves (indexes) in one kernel call; returns the new points' columns."""
    d = leaves.d
    x, at = pts["x"], pts["leaf"]
    is_active = np.zeros(len(leaves.cell), bool)
    is_active[active] = True
    n_old = len(x)
    if seed_cells:
        full = np.zeros(len(leaves.cell), bool)
        full[at] = True
        empty = active[~full[active]]
        mid = leaves.lo[empty] + (leaves.side[empty] // 2)[:, None]
        inn = domain.mask(mid) if len(mid) else np.zeros(0, bool)
        mid, empty = mid[inn], empty[inn]
        if len(mid):
            grid = Grid(d, spacing.most)
            grid.add(x, 0)
            ok = settle(mid, spacing.at(mid), grid, x, 1)
            mid, empty = mid[ok], empty[ok]
    else:
        mid, empty = np.zeros((0, d), np.int64), np.zeros(0, np.int64)
    waiting = is_active[at] & (pts["by_leaf"] != at) & ((pts["stage"] == stage) | ((pts["stage"] == stage - 1) & (pts["phase"] > leaves.colour[at])))
    w = np.flatnonzero(waiting)
    w = w[np.lexsort((pts["seq"][w], pts["rank"][w], pts["phase"][w], pts["stage"][w]))]
    base = np.concatenate([x, mid])
    home = np.concatenate([at, empty])
    front = np.concatenate([w, n_old + np.arange(len(mid))])
    where: list[np.ndarray] = [home]
    size = [len(base)]

    def owned(child, parent):
        leaf = leaves.of(child)
        flat = where[0] if len(where) == 1 else np.concatenate(where)
        where[:] = [flat, leaf]
        size[0] += len(leaf)
        return leaf == flat[parent]

    f = front_fill(base, front, spacing.at, domain.mask, dirs, spacing.most, owned=owned)
    flat = np.concatenate(where)
    new_x = np.concatenate([mid, f.x])
    leaf = np.concatenate([empty, flat[len(base) :]])
    by = np.concatenate([empty, flat[f.parent]])
    order = np.argsort(by, kind="stable")
    n = len(new_x)
    seq = np.zeros(n, np.int64)
    first = np.flatnonzero(np.diff(by[order], prepend=-1))
    seq[order] = np.arange(n) - np.repeat(first, np.diff(np.append(first, n)))
    return {
        "x": new_x,
        "leaf": leaf,
        "by_leaf": by,
        "h": spacing.at(new_x),
        "h_parent": np.concatenate([spacing.at(mid), f.h_parent]),
        "stage": np.full(n, stage),
        "phase": np.full(n, phase),
        "seq": seq,
        "rank": leaves.rank[by],
    }


def _join(parts: list[dict[str, np.ndarray]], d: int) -> dict[str, np.ndarray]:
    if not parts:
        z = np.zeros(0, np.int64)
        return {"x": np.zeros((0, d), np.int64), **{c: z for c in ("leaf", "by_leaf", "h", "h_parent", "stage", "phase", "seq", "rank")}}
    return {c: np.concatenate([p[c] for p in parts]) for c in parts[0]}


def phased_arrays(leaves: Leaves, domain: Domain, spacing: Spacing, k: int | None = None, max_stages: int = 64) -> dict[str, np.ndarray]:
    """The whole phased fill in one process, cell colours in order: the reference for the distributed form."""
    dirs = directions(leaves.d, k)
    tints = np.unique(leaves.colour)
    parts: list[dict[str, np.ndarray]] = []
    for stage in range(1, max_stages):
        went = False
        for c in tints.tolist():
            pts = _join(parts, leaves.d)
            mine = np.flatnonzero(leaves.colour == c)
            if stage > 1:
                w = (pts["by_leaf"] != pts["leaf"]) & (leaves.colour[pts["leaf"]] == c) & ((pts["stage"] == stage) | ((pts["stage"] == stage - 1) & (pts["phase"] > c)))
                mine = np.unique(pts["leaf"][w])
            if not len(mine):
                continue
            went = True
            parts.append(phase_cells(leaves, mine, pts, stage, c, domain, spacing, dirs, stage == 1))
        if not went:
            break
    else:
        raise RuntimeError("phased fill did not finish")
    return _join(parts, leaves.d)


def _table(leaves: Leaves, p: dict[str, np.ndarray], names: list[str]) -> pa.Table:
    cols = {n: p["x"][:, a] for a, n in enumerate(names)}
    cols |= {"h": p["h"], "h_parent": p["h_parent"], "cell": leaves.cell[p["leaf"]], "by_cell": leaves.cell[p["by_leaf"]]}
    cols |= {c: p[c] for c in ("stage", "phase", "seq", "rank")}
    return pa.table({c: pa.array(np.asarray(v), pa.int64()) for c, v in cols.items()})


def fill_phased(
    spark,
    domain: Domain,
    spacing: Spacing,
    cells: DataFrame | None = None,
    limit: int = 100,
    d: int = 2,
    k: int | None = None,
    one_task: bool = False,
    cells_per_task: int | None = None,
    max_stages: int = 64,
) -> DataFrame:
    """Fill a region from one seed a cell: ``x0.., h, h_parent, cell, by_cell, stage, phase, seq, rank``.

    ``cells`` is a work tree (``cell, level``; neighbours at most one level apart); by default the full tree for the least spacing and
    ``limit``.  ``one_task`` runs the same phases in one task and gives the same rows.  The leaf table is broadcast; it has a row for
    ``limit`` points, and its size is checked.  For fills beyond that check, or faster ones, see ``seams.fill_seams``.
    """
    level_parity = cells is not None
    if cells is None:
        cells = uniform(spark, uniform_level(limit, spacing.most, d), d)
    tinted = stored(colours(cells.select("cell", "level"), d, by_level=level_parity).select("cell", "level", "colour"))
    n_cells = tinted.count()
    if n_cells > 20_000_000:
        raise ValueError("leaf table too large to broadcast; raise the limit")
    flat = tinted.toPandas()
    leaves = Leaves(flat["cell"].to_numpy(), flat["level"].to_numpy(), flat["colour"].to_numpy().astype(np.int64), d)
    names = [f"x{a}" for a in range(d)]
    schema = point_schema(d)
    if one_task:
        if expected_points(domain, spacing, d) > ONE_TASK:
            raise ValueError("too many points for one task")

        def alone(_batches):
            for _ in _batches:
                pass
            yield from _table(leaves, phased_arrays(leaves, domain, spacing, k, max_stages), names).to_batches()

        return spark.range(1).repartition(1).mapInArrow(alone, schema)

    shared = spark.sparkContext.broadcast(leaves)
    dirs = directions(d, k)
    # enough tasks for the cores, and no more points in one than it can hold
    share = -(-n_cells // (len(np.unique(leaves.colour)) * 2 * spark.sparkContext.defaultParallelism))
    per_task = cells_per_task or max(1, min(share, int(400_000 // max(1, limit))))
    turn = np.zeros(n_cells, np.int64)
    for c in np.unique(leaves.colour).tolist():
        mine = np.flatnonzero(leaves.colour == c)
        turn[mine[np.argsort(leaves.rank[mine])]] = np.arange(len(mine)) // per_task
    n_tasks = int(turn.max()) + 1
    edges = neighbours(cells, d, include_self=True)
    boxes = spark.createDataFrame(flat.assign(rank=0).assign(cell=leaves.cell, level=leaves.level, colour=leaves.colour, rank=turn, **{f"lo{a}": leaves.lo[:, a] for a in range(d)}, side=leaves.side), "cell long, level long, colour long, rank long, " + ", ".join(f"lo{a} long" for a in range(d)) + ", side long")
    reach = stored(edges.join(boxes.select(F.col("cell").alias("nbr"), F.col("colour").alias("tint"), F.col("rank").alias("task"), *(f"lo{a}" for a in range(d)), "side"), "nbr"))
    points: DataFrame | None = None
    tints = np.unique(leaves.colour).tolist()
    gap = F.lit(2 * spacing.most)
    close = reduce(and_, ((F.col(n) >= F.col(f"lo{a}") - gap) & (F.col(n) < F.col(f"lo{a}") + F.col("side") + gap) for a, n in enumerate(names)))
    empty = spark.createDataFrame([], schema)

    def kernel(stage: int, c: int):
        def run(batches):
            got = [b for b in batches if b.num_rows]
            if not got:
                return
            table = pa.Table.from_batches(got)
            lv = shared.value
            real = table.filter(pa.compute.is_valid(table["x0"]))
            x = np.stack([real[n].to_numpy() for n in names], axis=1)
            if len(x):
                x, once = np.unique(x, axis=0, return_index=True)
            else:
                once = np.zeros(0, np.int64)
            order = np.argsort(lv.cell)
            find = lambda v: order[np.searchsorted(lv.cell, v, sorter=order)]
            pts = {"x": x, "leaf": lv.of(x), "by_leaf": find(real["by_cell"].to_numpy()[once])}
            pts |= {f: real[f].to_numpy()[once] for f in ("h", "h_parent", "stage", "phase", "seq", "rank")}
            mine = find(np.unique(table["target"].to_numpy()))
            yield from _table(lv, phase_cells(lv, mine, pts, stage, c, domain, spacing, dirs, stage == 1), names).to_batches()

        return run

    for stage in range(1, max_stages):
        went = False
        todo = None
        if stage > 1:
            held = points.where("by_cell <> cell").join(boxes.select("cell", "colour"), "cell").where((F.col("stage") == stage - 1) & (F.col("phase") > F.col("colour")))
            if held.isEmpty():
                break
        for c in tints:
            now = points if points is not None else empty
            if stage == 1:
                todo = boxes.where(F.col("colour") == c).select(F.col("cell").alias("target"))
            else:
                wait = now.where("by_cell <> cell").join(boxes.select("cell", "colour"), "cell").where(F.col("colour") == c)
                todo = wait.where((F.col("stage") == stage) | ((F.col("stage") == stage - 1) & (F.col("phase") > c))).select(F.col("cell").alias("target")).distinct()
                todo = stored(todo)
                if todo.isEmpty():
                    continue
            sent = now.join(reach.where(F.col("tint") == c), "cell").where(close).withColumn("target", F.col("nbr"))
            if stage > 1:
                sent = sent.join(todo, "target", "left_semi")
            rows = sent.select("task", "target", *names, *POINT)
            if stage == 1:
                # cells that no point reaches still have a seed to try
                bare = boxes.where(F.col("colour") == c).select(F.col("rank").alias("task"), F.col("cell").alias("target"))
                rows = rows.unionByName(bare, allowMissingColumns=True)
            # one partition a task: the rows of a task's cells meet, and nothing merges small partitions of costly cells
            new = stored(rows.repartitionById(n_tasks, F.col("task").cast("int")).mapInArrow(kernel(stage, c), schema))
            went = True
            points = new if points is None else points.unionByName(new)
        if not went:
            break
    else:
        raise RuntimeError("phased fill did not finish")
    return points
