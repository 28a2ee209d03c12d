"""The claims simulation: the points do not depend on how many supersteps one call of the kernel tests; its work is that of the points."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.directions import directions, propose
from frontfill.functions.kernel import Grid, Spots, Tiers, settle
from frontfill.functions.lattice import size_h
from frontfill.operators.tree import Leaves, uniform_level
from frontfill.plans import claims
from frontfill.plans.fill import seeds_relaxed


def simulated(n, workers, quantum, seek="none", limit=32):
    h = size_h(n)
    return claims.simulate(Leaves.uniform(uniform_level(limit, h, 2), 2), D.disc(), S.Constant(h), seeds_relaxed(D.disc(), workers, 2, seed=1), quantum, seed=1, seek=seek)


def told(r):
    cols = b"".join(np.asarray(c, np.int64).tobytes() for c in (r.x, r.worker, r.stage, r.step, r.h_parent, r.cell))
    return hashlib.sha256(cols + repr((sorted(r.counts.items()), r.busy, sorted(r.gaps.tolist()), r.owners_clash, r.unexpanded, r.left_in_set)).encode()).hexdigest()


@pytest.mark.parametrize("seek", ["none", "enqueued", "far", "unfilled"])
def test_supersteps_ahead_change_nothing(monkeypatch, seek):
    many = simulated(5000, 9, 8, seek)
    monkeypatch.setattr(claims, "AHEAD", 1)
    assert told(simulated(5000, 9, 8, seek)) == told(many)


def test_fewer_kernel_calls_than_supersteps(monkeypatch):
    calls = []
    settle = claims.settle
    monkeypatch.setattr(claims, "settle", lambda *a: calls.append(1) or settle(*a))
    r = simulated(20_000, 4, 8)
    assert r.unexpanded == 0 and len(calls) < r.counts["supersteps"] / 2


def test_tiers_find_what_a_grid_finds_and_move_rows_seldom(monkeypatch):
    x = np.random.default_rng(1).integers(0, 1 << 24, (60_000, 2))
    moved = []
    insert = np.insert
    monkeypatch.setattr(np, "insert", lambda a, *rest: moved.append(len(a)) or insert(a, *rest))
    one, many = Grid(2, 100_000), Tiers(2, 100_000)
    for i in range(0, len(x), 60):
        many.add(x[i : i + 60], i)
    assert sum(moved) < 100 * len(x)
    one.add(x, 0)
    pairs = [set(zip(*(v.tolist() for v in g.near(x[:500])), strict=True)) for g in (one, many)]
    assert pairs[0] == pairs[1]


def test_neighbours_of_a_full_tree_are_those_of_touching_boxes():
    leaves = Leaves.uniform(3, 2)
    for c, near in enumerate(claims.neighbour_lists(leaves)):
        gap = np.abs(leaves.lo - leaves.lo[c]).max(axis=1)
        assert sorted(near.tolist()) == np.flatnonzero((gap > 0) & (gap <= leaves.side[c])).tolist()


@pytest.mark.parametrize("seek", ["enqueued", "far", "unfilled"])
def test_idle_worker_takes_the_cell_that_looking_at_all_gives(seek):
    leaves = Leaves.uniform(4, 2)
    nbr = claims.neighbour_lists(leaves)
    rng = np.random.default_rng(3)
    for _ in range(30):
        cells = claims.Cells(leaves, nbr)
        cells.points[:-1] = rng.integers(0, 5, len(nbr))
        for c in rng.permutation(len(nbr)).tolist():
            state = int(rng.choice([0, 1, 2, 3, 3, 3], p=[0.6, 0.02, 0.02, 0.12, 0.12, 0.12]))
            cells.put(c, state, int(rng.integers(3)) if state in (1, 2) else -1)
            if state in (1, 3):
                cells.enter(c)
        options = [c for c in cells.entries() if cells.state[c] == 3 and all(not (cells.state[b] in (1, 2) and cells.owner[b] != 1) for b in nbr[c])]
        if seek == "unfilled":
            around = [cells.points[c] + sum(cells.points[b] for b in nbr[c]) for c in options]
            options = [c for c, k in zip(options, around, strict=True) if k == min(around)]
        gap = [min((((leaves.lo[m] - leaves.lo[c]) ** 2).sum() for m in cells.claimed), default=0) for c in options]
        want = -1 if not options else options[0] if seek == "enqueued" else options[int(np.argmax(gap))]
        assert cells.sought(1, seek) == want


def test_bound_on_supersteps_is_beyond_one_worker_on_fourteen_million_points():
    assert claims.step_bound(D.disc(), S.Constant(size_h(14_400_000)), 2) > 14_400_000 / 64


def test_each_configuration_has_a_task_of_its_own(spark):
    configs = [{"h": size_h(300), "workers": 2, "realisation": i} for i in range(4)]
    runs = claims.sweep(spark, configs, D.disc()).withColumn("part", F.spark_partition_id()).collect()
    assert sorted(r["realisation"] for r in runs) == [0, 1, 2, 3] and len({r["part"] for r in runs}) == 4


@pytest.mark.parametrize("seek", ["none", "far"])
def test_table_of_cells_gives_the_points_of_sorted_keys(monkeypatch, seek):
    h = size_h(5000)
    assert isinstance(claims.point_table(Leaves.uniform(4, 2), D.disc(), S.Constant(h)), Spots)
    table = told(simulated(5000, 9, 8, seek))
    monkeypatch.setattr(claims, "point_table", lambda leaves, domain, spacing: Tiers(2, spacing.most))
    assert told(simulated(5000, 9, 8, seek)) == table


def test_thin_region_or_changing_spacing_takes_sorted_keys():
    thin = D.Polygon(((0, 0), (16_000_000, 15_900_000), (16_000_000, 16_000_000)))
    assert isinstance(claims.point_table(Leaves.uniform(6, 2), thin, S.Constant(50_000)), Tiers)
    assert isinstance(claims.point_table(Leaves.uniform(4, 2), D.disc(), S.Linear(200_000, 400_000)), Tiers)


@pytest.mark.parametrize("h", [4, 7, 1000, 90_000])
@pytest.mark.parametrize("d", [1, 2])
def test_table_of_cells_finds_what_all_pairs_find(d, h):
    rng = np.random.default_rng(h)
    box = [(1000, 1000 + 30 * h)] * d
    x = rng.integers(1000, 1000 + 30 * h + 1, (2000, d))
    x = x[settle(x, np.full(len(x), h), Grid(d, h), x[:0], 1)]
    spots = Spots(box, h)
    spots.add(x, 0)
    cand = propose(x, np.full(len(x), h), directions(d))
    parent = np.repeat(np.arange(len(x)), cand.shape[1])
    cand = cand.reshape(-1, d)
    inside = ((cand >= 1000) & (cand <= 1000 + 30 * h)).all(axis=1)
    cand, parent = cand[inside], parent[inside]
    gap = ((cand[:, None, :] - x[None]) ** 2).sum(axis=2).min(axis=1)
    assert (spots.taken(cand, x.astype(np.int32), parent) == (gap < h * h)).all()


@pytest.mark.parametrize("d", [1, 2, 3])
@pytest.mark.parametrize("rings", [1, 2])
def test_candidates_in_chains_are_settled_as_one_by_one(d, rings):
    rng = np.random.default_rng(d)
    c = np.sort(rng.integers(0, 4000, (600, d)), axis=0)
    radius = rng.integers(20, 101, 600)
    good = []
    for i in range(600):
        if all(((c[i] - c[j]) ** 2).sum() >= radius[i] ** 2 for j in good):
            good.append(i)
    got = settle(c, radius, Grid(d, 100), c[:0], rings)
    assert np.flatnonzero(got).tolist() == good


def test_a_chain_is_not_a_round_a_link(monkeypatch):
    n = 5000
    calls = []
    count = np.flatnonzero
    monkeypatch.setattr(np, "flatnonzero", lambda a: calls.append(1) or count(a))
    zeros = np.zeros
    monkeypatch.setattr(np, "zeros", lambda *a, **k: calls.append(1) or zeros(*a, **k))
    x = np.arange(n)[:, None] * 60
    assert settle(x, np.full(n, 100), Grid(1, 100), x[:0], 1).tolist() == [i % 2 == 0 for i in range(n)] and len(calls) < 100
