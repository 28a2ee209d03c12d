"""Work cells claimed by competing workers: relational steps, and an exact simulation of the whole algorithm.

The relational steps (`arbitrate`, `release`, `enqueue`, `greedy_restart`) state the rules as joins.  `simulate` runs the complete
multi-stage algorithm for measurement: supersteps in which every worker expands a quantum of its front against the state of the
superstep before, and all claims are decided together.  A simulation is one task; sweeps over workers, sizes, limits and realisations
run one task a configuration.  `fill_claims_tasks` runs the same algorithm with a task a worker and superstep.
"""

from __future__ import annotations

import time
from collections import defaultdict, deque
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from frontfill.functions.directions import directions, propose
from frontfill.functions.kernel import Grid, Spots, Tiers, settle
from frontfill.functions.lattice import PRIME, SIDE, mix
from frontfill.operators.tree import Leaves
from frontfill.sources.store import stored

STATES = ("idle", "failed", "claimed", "enqueued")
#: from, event, to: what may happen to a cell
TRANSITIONS = {
    ("idle", "claim"): "claimed", ("idle", "refuse"): "failed", ("enqueued", "claim"): "claimed", ("enqueued", "refuse"): "failed",
    ("failed", "neighbour_released"): "enqueued", ("claimed", "dry"): "idle", ("failed", "stage_end"): "enqueued", ("enqueued", "put_back"): "enqueued",
}


def arbitrate(requests: DataFrame, state: DataFrame, edges: DataFrame) -> DataFrame:
    """``cell, worker, granted`` for one round of ``requests(worker, cell)``.

    For each cell the request of smallest hashed rank stands for it.  It is granted if the cell is idle or enqueued, no neighbour is held
    or flagged by another worker (``state(cell, state, owner)``), and no neighbour's standing request of another worker ranks before it.
    """
    rank = F.struct(mix(mix(F.col("cell") % 2147483647) + F.col("worker")).alias("r"), F.col("worker").alias("w"), F.col("cell").alias("c"))
    asked = requests.select("worker", "cell").distinct().withColumn("rank", rank)
    stand = asked.groupBy("cell").agg(F.min("rank").alias("rank")).select("cell", "rank", F.col("rank.w").alias("worker"))
    flags = state.where(F.col("state").isin("claimed", "failed")).select("cell", "owner")
    taken = flags.select("cell").distinct()
    barred = stand.join(edges, "cell").join(flags.select(F.col("cell").alias("nbr"), "owner"), "nbr").where("owner <> worker").select("cell").distinct()
    rival = stand.select(F.col("cell").alias("nbr"), F.col("worker").alias("w2"), F.col("rank").alias("rank2"))
    beaten = stand.join(edges, "cell").join(rival, "nbr").where("w2 <> worker").where(F.col("rank2") < F.col("rank")).select("cell").distinct()
    no = barred.union(beaten).union(taken).distinct().withColumn("no", F.lit(True))
    won = stand.join(no, "cell", "left").select("cell", F.col("worker").alias("winner"), F.col("no").isNull().alias("open"))
    return asked.join(won, "cell").select("cell", "worker", (F.col("open") & (F.col("worker") == F.col("winner"))).alias("granted"))


def release(state: DataFrame, edges: DataFrame) -> DataFrame:
    """The state after cells whose owner has no front points left are let go: they fall idle, and cells next to them on which that owner failed become enqueued."""
    dry = state.where("state = 'claimed' and front_count = 0").select("cell", "owner")
    freed = dry.join(edges, "cell").select(F.col("nbr").alias("cell"), F.col("owner").alias("by")).distinct()
    hit = state.where("state = 'failed'").select("cell", "owner").join(freed, "cell").where("owner = by").select("cell").distinct().withColumn("free", F.lit(True))
    let = dry.select("cell").withColumn("let", F.lit(True))
    out = state.join(hit, "cell", "left").join(let, "cell", "left")
    new = F.when(F.col("let"), "idle").when(F.col("free"), "enqueued").otherwise(F.col("state"))
    return out.select("cell", new.alias("state"), F.when(F.col("let") | F.col("free"), F.lit(None)).otherwise(F.col("owner")).cast("int").alias("owner"), F.when(F.col("let"), 0).otherwise(F.col("front_count")).cast("int").alias("front_count"))


def enqueue(entries: DataFrame) -> DataFrame:
    """The restart set: the first entry of each cell, in order of arrival ``ord``."""
    first = entries.groupBy("cell").agg(F.min(F.struct("stage", "step", "ord", "point")).alias("e"))
    return first.select("cell", "e.point", "e.stage", "e.step", "e.ord")


def restart_order(restart: DataFrame, order: str = "fifo", seed: int = 1) -> DataFrame:
    """The set with ``place``: first-in-first-out, or shuffled by a hash."""
    by = [F.col("stage"), F.col("step"), F.col("ord")] if order == "fifo" else [mix(mix(F.col("cell") % 2147483647) + seed), F.col("cell")]
    key = F.struct(*by)
    # ranks over the whole set: cells, not points, one stage's worth
    return restart.withColumn("place", F.row_number().over(Window.orderBy(key)))


def greedy_restart(ordered: DataFrame, edges: DataFrame, workers: int) -> DataFrame:
    """Cells that restart, one a worker, taken in order when no neighbour has been taken: ``cell, place, worker``.

    An entry with no undecided earlier neighbour is settled each round, so the greedy answer comes in a few joins.
    """
    live = stored(ordered.select("cell", "place"))
    taken = None
    while True:
        rival = live.select(F.col("cell").alias("nbr"), F.col("place").alias("p2"))
        held = live.join(edges, "cell").join(rival, "nbr").where("p2 < place").select("cell").distinct()
        now = stored(live.join(held, "cell", "left_anti"))
        if now.isEmpty():
            break
        taken = now if taken is None else taken.unionByName(now)
        gone = now.select("cell").union(now.join(edges, "cell").select(F.col("nbr").alias("cell"))).distinct()
        live = stored(live.join(gone, "cell", "left_anti"))
        if live.isEmpty():
            break
    if taken is None:
        return ordered.where(F.lit(False)).select("cell", "place", F.lit(0).alias("worker"))
    return taken.orderBy("place").limit(workers).withColumn("worker", F.row_number().over(Window.orderBy("place")) - 1)


@dataclass
class Report:
    x: np.ndarray
    worker: np.ndarray
    stage: np.ndarray
    step: np.ndarray
    h_parent: np.ndarray
    cell: np.ndarray
    counts: dict = field(default_factory=dict)
    busy: list = field(default_factory=list)
    #: width in cells of the gap at each unfilled cell between two owners, when the first stage ends
    gaps: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    owners_clash: int = 0
    unexpanded: int = 0
    left_in_set: int = 0


class Near:
    """Neighbours of each cell as rows of one table, filled up with the number of cells."""

    def __init__(self, table: np.ndarray):
        self.table = table
        self.many = (table < len(table)).sum(axis=1).tolist()

    def __len__(self) -> int:
        return len(self.many)

    def __getitem__(self, c: int) -> np.ndarray:
        return self.table[c, : self.many[c]]


def neighbour_lists(leaves: Leaves) -> Near:
    """Vertex neighbours of each leaf of a full or mixed tree, by touching boxes on the grid of the coarsest cells."""
    d = leaves.d
    wide = int(leaves.side.max())
    slot = leaves.lo // wide
    if (leaves.side == wide).all() and len(slot) == (SIDE // wide) ** d:
        n = len(slot)
        leaf = np.full([SIDE // wide + 2] * d, n, np.int32)
        leaf[tuple(slot.T + 1)] = np.arange(n)
        shifts = [o for o in np.ndindex(*([3] * d)) if any(v != 1 for v in o)]
        near = np.stack([leaf[tuple(slot[:, a] + o[a] for a in range(d))] for o in shifts], axis=1)
        # a cell at the border has fewer: what is missing goes to the end, the rest keeps its order
        rim = np.flatnonzero((near == n).any(axis=1))
        near[rim] = np.take_along_axis(near[rim], np.argsort(near[rim] == n, axis=1, kind="stable"), axis=1)
        return Near(near)
    table = defaultdict(list)
    for i, s in enumerate(map(tuple, slot.tolist())):
        table[s].append(i)
    out = []
    hi = leaves.lo + leaves.side[:, None]
    for i in range(len(leaves.cell)):
        near = [j for o in np.ndindex(*([3] * d)) for j in table.get(tuple(int(slot[i, a]) + o[a] - 1 for a in range(d)), ())]
        near = np.array([j for j in near if j != i], np.int64)
        touch = np.all((leaves.lo[near] <= hi[i]) & (hi[near] >= leaves.lo[i]), axis=1) if len(near) else np.zeros(0, bool)
        out.append(near[touch])
    table = np.full((len(out), max(map(len, out), default=0)), len(out), np.int32)
    for i, near in enumerate(out):
        table[i, : len(near)] = near
    return Near(table)


def gap_widths(nbr: Near, owner: np.ndarray) -> np.ndarray:
    """Cells on the shortest way from one owner's area to another's through each unfilled cell (``owner`` -1; less for cells that do not count); cells that fewer than two reach are left out.

    Areas spread through unfilled cells a ring at a time; each cell keeps the two nearest different owners and their distances.
    """
    reached: list[dict[int, int]] = [{int(o): 0} if o >= 0 else {} for o in owner]
    ring = [(c, int(o)) for c, o in enumerate(owner.tolist()) if o >= 0]
    hops = 0
    while ring:
        hops += 1
        after = []
        for c, o in ring:
            for b in nbr[c].tolist():
                if owner[b] == -1 and o not in reached[b] and len(reached[b]) < 2:
                    reached[b][o] = hops
                    after.append((b, o))
        ring = after
    return np.array([sum(r.values()) - 1 for r, o in zip(reached, owner.tolist(), strict=True) if o == -1 and len(r) == 2], np.int64)


def _candidates(x: np.ndarray, spacing, domain, dirs: np.ndarray):
    """(candidates inside, place of the parent of each, radius of each, how many lie outside)"""
    ph = spacing.at(x)
    cand = propose(x, ph, dirs)
    at, radius = np.repeat(np.arange(len(x)), cand.shape[1]), np.repeat(ph, cand.shape[1])
    cand = cand.reshape(-1, x.shape[1])
    inn = domain.mask(cand)
    return cand[inn], at[inn], radius[inn], int((~inn).sum())


class Cells:
    """State, owner and restart set of the cells.  Where idle workers seek cells, for each cell the flags (failed or claimed) next to it are kept as a number,
    a sum of owners and a sum of their squares: all of them are one worker's if and only if both sums are that number's multiples, whatever their order."""

    def __init__(self, leaves: Leaves, nbr: Near, seeking: bool = True):
        n = len(leaves.cell)
        self.nbr, self.lo = nbr, leaves.lo
        self.state = bytearray(n)
        self.states = np.frombuffer(self.state, np.uint8)
        self.owner = [-1] * n
        self.owners = np.full(n, -1, np.int32)
        self.flags = np.zeros((n, 3), np.int64) if seeking else None
        #: place in the restart set by order of entry; -1: not in it
        self.place = np.full(n, -1, np.int64)
        self.entered = self.waiting = 0
        self.points = np.zeros(n + 1, np.int64)
        self.claimed: set[int] = set()
        #: claimed neighbours of different owners, counted from both
        self.clashes = 0

    def put(self, c: int, state: int, owner: int) -> None:
        was, by = self.state[c], self.owner[c]
        if self.flags is not None:
            if was in (1, 2):
                self.flags[self.nbr[c]] -= (1, by, by * by)
            if state in (1, 2):
                self.flags[self.nbr[c]] += (1, owner, owner * owner)
        if was == 2:
            self.clashes -= 2 * self._rivals(c, by)
            self.claimed.discard(c)
        if state == 2:
            self.clashes += 2 * self._rivals(c, owner)
            self.claimed.add(c)
        self.state[c], self.owner[c], self.owners[c] = state, owner, owner

    def _rivals(self, c: int, w: int) -> int:
        n, state, owner = 0, self.state, self.owner
        for b in self.nbr[c].tolist():
            if state[b] == 2 and owner[b] != w:
                n += 1
        return n

    def free_of_others(self, c: int, w: int) -> bool:
        state, owner = self.state, self.owner
        for b in self.nbr[c].tolist():
            if owner[b] != w and state[b] in (1, 2):
                return False
        return True

    def enter(self, c: int) -> bool:
        """Put a cell at the end of the restart set; was it not there?"""
        if self.place[c] >= 0:
            return False
        self.place[c] = self.entered
        self.entered += 1
        self.waiting += 1
        return True

    def leave(self, c: int) -> None:
        self.waiting -= int(self.place[c] >= 0)
        self.place[c] = -1

    def entries(self) -> list[int]:
        """The restart set in order."""
        c = np.flatnonzero(self.place >= 0)
        return c[np.argsort(self.place[c])].tolist()

    def sought(self, w: int, seek: str) -> int:
        """The enqueued cell that an idle worker takes, -1 for none."""
        c = np.flatnonzero(self.states == 3)
        n, one, two = self.flags[c].T
        c = c[(one == n * w) & (two == n * w * w) & (self.place[c] >= 0)]
        if not len(c):
            return -1
        if seek == "enqueued":
            return int(c[self.place[c].argmin()])
        if seek == "unfilled":
            k = self.points[c] + self.points[self.nbr.table[c]].sum(axis=1)
            c = c[k == k.min()]
        c = c[np.argsort(self.place[c])]
        gap = np.full(len(c), np.iinfo(np.int64).max if self.claimed else 0)
        for m in self.claimed:
            gap = np.minimum(gap, ((self.lo[c] - self.lo[m]) ** 2).sum(axis=1))
        return int(c[gap.argmax()])


class Columns:
    """Arrays that grow at their end at a cost in proportion to what is added."""

    def __init__(self, **kinds):
        self.n = 0
        self._held = {c: np.zeros((1024, *shape), kind) for c, (kind, shape) in kinds.items()}

    def __getitem__(self, c: str) -> np.ndarray:
        return self._held[c][: self.n]

    def add(self, n: int, **values) -> None:
        for c, v in values.items():
            held = self._held[c]
            if self.n + n > len(held):
                held = np.zeros((max(self.n + n, len(held) * 3 // 2), *held.shape[1:]), held.dtype)
                held[: self.n] = self._held[c][: self.n]
                self._held[c] = held
            held[self.n : self.n + n] = v
        self.n += n


def step_bound(domain, spacing, d: int) -> int:
    """More supersteps than a fill can need: each expands a point at least."""
    from frontfill.plans.fill import expected_points

    return max(200_000, 4 * int(expected_points(domain, spacing, d)))


def point_table(leaves: Leaves, domain, spacing) -> Spots | Tiers:
    """A table of cells where one spacing fills the region's box evenly, sorted keys elsewhere."""
    box = domain.box()
    if box is not None and leaves.d <= 2 and spacing.least == spacing.most:
        inside = leaves.side[domain.mask(leaves.lo + (leaves.side // 2)[:, None])].astype(np.float64) ** leaves.d
        if 4 * inside.sum() >= np.prod([hi - lo + 1.0 for lo, hi in box]):
            return Spots(box, spacing.most)
    return Tiers(leaves.d, spacing.most)


#: about how many points one call of the kernel expands for supersteps to come
AHEAD = 4096


def simulate(leaves: Leaves, domain, spacing, seeds: np.ndarray, quantum: int = 64, order: str = "shuffled", seed: int = 1, k: int | None = None, seek: str = "none", max_steps: int | None = None, expand=None) -> Report:
    """The claiming fill with one worker a seed.  ``seek`` lets an idle worker take an enqueued cell within a stage.

    ``enqueued`` takes the oldest, ``far`` the one farthest from claimed cells, ``unfilled`` of those with the fewest points in and around
    them the one farthest from claimed cells.  ``expand(points, workers, nbr)`` does the expansions of a superstep elsewhere and
    returns the accepted candidates, their parents' places in the list and their radii, in order; claims are always decided here.

    A superstep costs its quanta and the claims they lead to, not the points or cells there are.  Children join the end of their worker's queue, so what the
    next supersteps expand is known as far as every queue reaches, and one call of the kernel tests the candidates of them all, in order.  ``max_steps`` is by default more than the
    points of the fill, each superstep expanding one at least.
    """
    d, W = leaves.d, len(seeds)
    dirs = directions(d, k)
    nbr = neighbour_lists(leaves)
    n_cells = len(leaves.cell)
    max_steps = max_steps or step_bound(domain, spacing, d)
    cells = Cells(leaves, nbr, seek != "none")
    state, owner = cells.state, cells.owner
    front_count = np.zeros(n_cells, np.int64)
    #: points that no front holds yet, by cell
    unheld: dict[int, list[int]] = defaultdict(list)
    rng = np.random.default_rng(seed)
    count = dict.fromkeys(("attempts", "grants", "fails", "entries", "releases", "supersteps", "stages", "tested", "outside", "blocked", "put_back"), 0)
    grid = point_table(leaves, domain, spacing)
    pts = Columns(x=(np.int32, (d,)), cell=(np.int32, ()), worker=(np.int32, ()), stage=(np.int32, ()), step=(np.int32, ()), h=(np.int32, ()), expanded=(bool, ()))
    fronts: list[deque[int]] = [deque() for _ in range(W)]
    #: of supersteps to come: points, workers, accepted candidates, their cells, parents' places and radii
    ahead: deque[tuple] = deque()
    busy: list[tuple[int, int]] = []
    gaps = np.zeros(0, np.int64)
    clash = 0

    def add(x, c, w, stage, step, radius):
        first = pts.n
        pts.add(len(x), x=x, cell=c, worker=w, stage=stage, step=step, h=radius, expanded=False)
        np.add.at(cells.points, c, 1)
        return range(first, first + len(x))

    def enqueue_cell(c):
        count["entries"] += cells.enter(c)

    def grant(c, w):
        cells.put(c, 2, w)
        cells.leave(c)
        waiting = unheld.pop(c, [])
        fronts[w].extend(waiting)
        front_count[c] = len(waiting)
        count["grants"] += 1

    def drop(c):
        w = owner[c]
        cells.put(c, 0, -1)
        count["releases"] += 1
        for b in nbr[c].tolist():
            if state[b] == 1 and owner[b] == w:
                cells.put(b, 3, -1)
                enqueue_cell(b)

    def settle_claims(asked):
        """Decide all claims of a superstep together: smallest hashed rank first in each neighbourhood."""
        if not asked:
            return
        by, of = np.array(list(asked), np.int64).T
        rank = np.lexsort((of, by, mix(mix(leaves.cell[of] % PRIME) + by)))
        for w, c in zip(by[rank].tolist(), of[rank].tolist(), strict=True):
            count["attempts"] += 1
            if state[c] == 2:
                count["fails"] += owner[c] != w
                continue
            if state[c] in (0, 3) and cells.free_of_others(c, w):
                grant(c, w)
                continue
            count["fails"] += 1
            if state[c] != 1:
                cells.put(c, 1, w)
                enqueue_cell(c)

    seeds = np.asarray(seeds, np.int64)
    ok = domain.mask(seeds)
    ok[ok] = settle(seeds[ok], spacing.at(seeds[ok]), grid, pts["x"], 1)
    grid.add(seeds[ok], 0)
    at_cells = leaves.of(seeds[ok])
    for i, c in zip(add(seeds[ok], at_cells, np.flatnonzero(ok), 1, 0, spacing.at(seeds[ok])), at_cells.tolist(), strict=True):
        unheld[c].append(i)
    settle_claims([(int(w), int(c)) for w, c in zip(np.flatnonzero(ok), at_cells, strict=True)])
    for c in at_cells.tolist():
        if state[c] == 0:
            enqueue_cell(c)
            cells.put(c, 3, -1)
    stage, step = 1, 0
    while step < max_steps:
        if not ahead and not any(fronts):
            # stage end: what failed may be claimed again
            held = np.flatnonzero((cells.states == 1) | (cells.states == 3)).tolist()
            if stage == 1:
                # an area is what one worker has filled and expanded; a cell that waits belongs to none, one outside the region does not count
                area = np.where((cells.points[:n_cells] > 0) | domain.mask(leaves.lo + (leaves.side // 2)[:, None]), -1, -2)
                done = (cells.points[:n_cells] > 0) & (cells.states == 0)
                done[pts["cell"][~pts["expanded"]]] = False
                pair, many = np.unique(pts["cell"].astype(np.int64) * W + pts["worker"], return_counts=True)
                best = np.lexsort((-(pair % W), many, pair // W))
                last = best[np.flatnonzero(np.diff(pair[best] // W, append=-1))]
                most = np.full(n_cells, -1)
                most[pair[last] // W] = pair[last] % W
                area = np.where(done, most, area)
                gaps = gap_widths(nbr, area)
            for c in held:
                cells.put(c, 3, -1)
                enqueue_cell(c)
            if not cells.waiting:
                break
            stage += 1
            entries = cells.entries()
            cells.place[:] = -1
            cells.waiting = 0
            if order == "shuffled":
                rng.shuffle(entries)
            w = 0
            for c in entries:
                if w < W and cells.free_of_others(c, w) and state[c] == 3:
                    grant(c, w)
                    w += 1
                else:
                    count["put_back"] += 1
                    cells.enter(c)
        step += 1
        if seek != "none" and not ahead:
            for w in range(W):
                if not fronts[w] and cells.waiting:
                    c = cells.sought(w, seek)
                    if c >= 0:
                        grant(c, w)
        if not ahead and any(fronts):
            at_work = [len(f) for f in fronts if f]
            known = expand is None and (seek == "none" or len(at_work) == W)
            sent, by, end = [], [], []
            for _ in range(max(1, min(min(at_work), AHEAD // len(at_work)) // quantum) if known else 1):
                for w, f in enumerate(fronts):
                    take = min(quantum, len(f))
                    sent += [f.popleft() for _ in range(take)]
                    by += [w] * take
                end.append(len(sent))
            now, who = np.array(sent), np.array(by)
            x = pts["x"][now].astype(np.int64)
            if expand is None:
                cand, at, radius, outside = _candidates(x, spacing, domain, dirs)
                good = settle(cand, radius, grid, pts["x"], 1, now[at])
                cand, at, radius, blocked = cand[good], at[good], radius[good], int((~good).sum())
                grid.add(cand, pts.n)
            else:
                cand, at, radius, outside, blocked = expand(x, who, nbr)
            count["tested"] += len(cand) + outside + blocked
            count["outside"] += outside
            count["blocked"] += blocked
            of = leaves.of(cand)
            for i, j in zip([0, *end], end, strict=False):
                a, b = (0, len(at)) if len(end) == 1 else np.searchsorted(at, (i, j))
                ahead.append((now[i:j], who[i:j], cand[a:b], of[a:b], at[a:b] - i, radius[a:b]))
        now, who, cand, at_cells, at, radius = ahead.popleft() if ahead else ((),) * 6
        # workers stand in order
        busy.append((stage, int(np.count_nonzero(np.diff(who, prepend=-1)))))
        if len(now):
            w = who[at]
            ids = np.array(add(cand, at_cells, w, stage, step, radius), np.int64)
            pts["expanded"][now] = True
            held = (cells.states[at_cells] == 2) & (cells.owners[at_cells] == w)
            np.add.at(front_count, at_cells[held], 1)
            joins, to = ids[held].tolist(), w[held]
            cut = np.flatnonzero(np.diff(to, prepend=-1)).tolist()
            for a, b in zip(cut, [*cut[1:], len(joins)], strict=False):
                fronts[to[a]].extend(joins[a:b])
            asked = set()
            for i, c, ww in zip(ids[~held].tolist(), at_cells[~held].tolist(), w[~held].tolist(), strict=True):
                unheld[c].append(i)
                asked.add((ww, c))
            settle_claims(asked)
            cell_of = pts["cell"][now]
            np.subtract.at(front_count, cell_of, 1)
            cell_of = np.unique(cell_of)
            for c in cell_of[(cells.states[cell_of] == 2) & (front_count[cell_of] <= 0)].tolist():
                drop(c)
        clash += cells.clashes
    else:
        raise RuntimeError("claims did not finish")
    count["supersteps"], count["stages"] = step, stage
    return Report(pts["x"].astype(np.int64), pts["worker"], pts["stage"], pts["step"], pts["h"], leaves.cell[pts["cell"]], count, busy, gaps, clash, int((~pts["expanded"]).sum()), cells.waiting)


RUN = "run string, method string, h long, lim long, workers int, realisation int, n long, stages long, supersteps long, attempts long, grants long, fails long, entries long, releases long, put_back long, tested long, outside long, blocked long, gap_one long, gap_two long, gap_wider long, stage1_points long, stage1_steps long, active double, owners_clash long, unexpanded long, left_in_set long, seconds double"


def sweep(spark, configs: list[dict], domain, d: int = 2) -> DataFrame:
    """One row a configuration ``{h, limit, workers, realisation, quantum, order, seek}``, simulated in parallel tasks."""
    from frontfill.functions.spacing import Constant
    from frontfill.operators.tree import uniform_level
    from frontfill.plans.fill import seeds_relaxed

    rows = [{"h": c["h"], "lim": c.get("limit", 100), "workers": c["workers"], "realisation": c.get("realisation", 0), "quantum": c.get("quantum", 64), "ord": c.get("order", "shuffled"), "seek": c.get("seek", "none")} for c in configs]
    # a range deals one number to each task; by hash several would meet in one
    frame = spark.range(0, len(rows), 1, max(1, len(rows)))

    def run(batches):
        for b in batches:
            for c in (rows[i] for i in b["id"].to_pylist()):
                sp = Constant(c["h"])
                leaves = Leaves.uniform(uniform_level(c["lim"], c["h"], d), d)
                t = time.perf_counter()
                r = simulate(leaves, domain, sp, seeds_relaxed(domain, c["workers"], d, seed=c["realisation"] + 1), c["quantum"], c["ord"], c["realisation"] + 1, seek=c["seek"])
                t = time.perf_counter() - t
                steps1 = sum(1 for s, _ in r.busy if s == 1)
                row = {"run": f"{c['h']}/{c['lim']}/{c['workers']}/{c['realisation']}", "method": "claims", "h": c["h"], "lim": c["lim"], "workers": c["workers"], "realisation": c["realisation"], "n": len(r.x), "stage1_points": int((r.stage == 1).sum()), "stage1_steps": steps1}
                row |= {x: r.counts[x] for x in ("stages", "supersteps", "attempts", "grants", "fails", "entries", "releases", "put_back", "tested", "outside", "blocked")}
                row |= {"gap_one": int((r.gaps == 1).sum()), "gap_two": int((r.gaps == 2).sum()), "gap_wider": int((r.gaps > 2).sum())}
                row |= {"active": sum(w for _, w in r.busy) / max(1, len(r.busy) * c["workers"]), "owners_clash": r.owners_clash, "unexpanded": r.unexpanded, "left_in_set": r.left_in_set, "seconds": t}
                yield pa.RecordBatch.from_pylist([row], schema)

    kinds = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "double": pa.float64()}
    schema = pa.schema([(f.split()[0], kinds[f.split()[1]]) for f in RUN.split(", ")])
    return frame.mapInArrow(run, RUN)


def fill_claims(spark, domain, spacing, workers: int, limit: int = 100, d: int = 2, quantum: int = 64, order: str = "shuffled", seed: int = 1, seek: str = "none", seeds=None) -> DataFrame:
    """Points of one simulated claiming fill: ``ord, x0.., h_parent, worker, stage, step, cell``."""
    from frontfill.operators.tree import uniform_level
    from frontfill.plans.fill import seeds_relaxed

    leaves = Leaves.uniform(uniform_level(limit, spacing.most, d), d)
    start = seeds_relaxed(domain, workers, d, seed=seed) if seeds is None else np.asarray(seeds, np.int64)

    def run(batches):
        for _ in batches:
            pass
        r = simulate(leaves, domain, spacing, start, quantum, order, seed, seek=seek)
        cols = {"ord": np.arange(len(r.x)), **{f"x{a}": r.x[:, a] for a in range(d)}, "h_parent": r.h_parent, "worker": r.worker, "stage": r.stage, "step": r.step, "cell": r.cell}
        yield pa.RecordBatch.from_pydict({c: pa.array(v, pa.int64()) for c, v in cols.items()})

    return spark.range(1).repartition(1).mapInArrow(run, "ord long, " + ", ".join(f"x{a} long" for a in range(d)) + ", h_parent long, worker long, stage long, step long, cell long")


#: the coordinator of a parallel run holds the cells, the fronts and each point's cell; more points than this are refused
MOST_POINTS = 20_000_000


def fill_claims_tasks(spark, domain, spacing, workers: int, limit: int = 100, d: int = 2, quantum: int = 256, order: str = "shuffled", seed: int = 1, seek: str = "none", seeds=None, merge_every: int = 8) -> DataFrame:
    """The claiming fill run in parallel: ``x0.., h_parent, worker, step, ord, cell``, the points of ``fill_claims``.

    A superstep is one job: a task for each worker expands a quantum of its front against the stored points in the cells of that
    quantum and next to them, and stores what it accepts.  Workers never hold neighbouring cells, which are three spacings wide, so no candidate of one can clash
    with another's.  The coordinator decides the claims between the jobs, from the cells of the new points.
    """
    from frontfill.operators.tree import uniform_level
    from frontfill.plans.fill import expected_points, seeds_relaxed, thin_seeds

    if expected_points(domain, spacing, d) > MOST_POINTS:
        raise ValueError("too many points for one coordinator; use seams.fill_seams")
    leaves = Leaves.uniform(uniform_level(limit, spacing.most, d), d)
    start = seeds_relaxed(domain, workers, d, seed=seed) if seeds is None else np.asarray(seeds, np.int64)
    names = [f"x{a}" for a in range(d)]
    dirs = directions(d)
    schema = ", ".join(f"{c} long" for c in (*names, "h_parent", "worker", "step", "ord", "cell", "at", "outside", "blocked"))
    first = thin_seeds(start, spacing.at(start), domain.mask(start), spacing.most)
    owner = {tuple(p): w for w, p in reversed(list(enumerate(start.tolist())))}
    rows = [(*p, int(spacing.at(np.array([p]))[0]), owner[tuple(p)], 0, i, int(leaves.cell[leaves.of(np.array([p]))[0]]), -1, 0, 0) for i, p in enumerate(first.tolist())]
    parts = [stored(spark.createDataFrame(rows, schema))]
    shared = spark.sparkContext.broadcast(leaves)
    step = 0

    def task(key, front, near):
        front = front.sort_by("at")
        x = np.stack([front[n].to_numpy() for n in names], axis=1)
        known = np.stack([near[n].to_numpy() for n in names], axis=1) if near.num_rows else np.zeros((0, d), np.int64)
        cand, at, radius, outside = _candidates(x, spacing, domain, dirs)
        grid = Grid(d, spacing.most)
        grid.add(known, 0)
        good = settle(cand, radius, grid, known, 1)
        x, n = cand[good], int(good.sum())
        lv = shared.value
        cols = {nm: x[:, a] for a, nm in enumerate(names)} | {"h_parent": radius[good], "cell": lv.cell[lv.of(x)], "ord": np.arange(n), "at": front["at"].to_numpy()[at[good]]}
        cols |= {c: np.full(n, v) for c, v in (("worker", key[0].as_py()), ("step", front["step"][0].as_py()), ("outside", 0), ("blocked", 0))}
        # one more row without a place carries the counts
        told = {c: pa.array([*np.asarray(v).tolist(), None], pa.int64()) for c, v in cols.items()}
        told["worker"] = pa.array([key[0].as_py()] * (n + 1), pa.int64())
        told["outside"], told["blocked"] = (pa.array([0] * n + [v], pa.int64()) for v in (outside, int((~good).sum())))
        return pa.table({c.split()[0]: told[c.split()[0]] for c in schema.split(", ")})

    def expand(x, who, nbr):
        nonlocal step, parts
        step += 1
        sent = spark.createDataFrame([(int(w), i, step, *map(int, p)) for i, (p, w) in enumerate(zip(x, who, strict=True))], "worker long, at long, step long, " + ", ".join(f"{n} long" for n in names))
        # a row for each cell next to the quantum, bounded by it
        seen = {(int(leaves.cell[b]), int(w)) for c, w in zip(leaves.of(x).tolist(), who.tolist(), strict=True) for b in (c, *nbr[c].tolist())}
        cells = spark.createDataFrame(sorted(seen), "cell long, to long")
        if len(parts) > merge_every:
            parts = [stored(reduce(DataFrame.unionByName, parts))]
        near = reduce(DataFrame.unionByName, parts).select("cell", *names).join(F.broadcast(cells), "cell").select(F.col("to").alias("worker"), *names)
        out = stored(sent.groupBy("worker").cogroup(near.groupBy("worker")).applyInArrow(task, schema))
        parts.append(out.where("x0 is not null"))
        # what a superstep adds: at most the candidates of its quanta
        got = out.select(*names, "h_parent", "worker", "ord", "at", "outside", "blocked").orderBy("worker", "ord").toArrow()
        real = got.filter(pa.compute.is_valid(got["x0"]))
        new = np.stack([real[n].to_numpy() for n in names], axis=1) if real.num_rows else np.zeros((0, d), np.int64)
        return new, real["at"].to_numpy().astype(np.int64), real["h_parent"].to_numpy().astype(np.int64), pa.compute.sum(got["outside"]).as_py(), pa.compute.sum(got["blocked"]).as_py()

    simulate(leaves, domain, spacing, start, quantum, order, seed, seek=seek, expand=expand)
    return reduce(DataFrame.unionByName, parts).select(*names, "h_parent", "worker", "step", "ord", "cell")
