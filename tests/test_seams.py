"""The fill by blocks and seams: same points from one process and from tasks, complete and without violations."""

import numpy as np
import pytest

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.directions import directions, propose
from frontfill.functions.kernel import Grid
from frontfill.functions.lattice import size_h
from frontfill.plans import claims, fill, seams

CASES = [
    ("disc", D.disc(), S.Constant(size_h(3000)), 2, 600),
    ("parts", (D.disc() - D.Box((7_000_000, 7_000_000), (9_000_000, 9_000_000))) | D.Box((100, 100), (300_000, 15_000_000)), S.Constant(150_000), 2, 600),
    ("linear", D.disc(), S.Linear(100_000, 260_000), 2, 600),
    ("corner", D.Ball((5_592_406, 5_592_406), 500_000), S.Constant(90_000), 2, 600),
    ("segment", D.Box((100,), (16_000_000,)), S.Constant(20_000), 1, 100),
    ("ball", D.disc(d=3), S.Constant(500_000), 3, 3000),
]


def audit(p, domain, spacing, d):
    """(pairs nearer than both were tested with, candidates that are inside and free)"""
    x, r = p["x"], p["h_parent"]
    grid = Grid(d, spacing.most)
    grid.add(x, 0)
    a, b = grid.near(x, 1)
    gap = ((x[a] - x[b]) ** 2).sum(axis=1)
    cand = propose(x, spacing.at(x), directions(d))
    radius = np.repeat(spacing.at(x), cand.shape[1])
    cand = cand.reshape(-1, d)
    inn = domain.mask(cand)
    cand, radius = cand[inn], radius[inn]
    q, k = grid.near(cand, 1)
    free = np.ones(len(cand), bool)
    free[q[((cand[q] - x[k]) ** 2).sum(axis=1) < radius[q] ** 2]] = False
    return int(((a != b) & (gap < np.minimum(r[a], r[b]) ** 2)).sum()), int(free.sum())


@pytest.mark.parametrize("name,domain,spacing,d,block", CASES, ids=[c[0] for c in CASES])
def test_complete_and_apart(name, domain, spacing, d, block):
    p = seams.seam_arrays(domain, spacing, d, block_points=block)
    assert len(p["x"]) > 20 and domain.mask(p["x"]).all()
    assert audit(p, domain, spacing, d) == (0, 0)
    zones = seams.Zones(spacing, d, block)
    home, family = zones.home(p["x"])
    assert (home == p["zone"]).all() and (family == p["family"]).all()


@pytest.mark.parametrize("tasks", [3, 16])
def test_tasks_give_the_same_points(spark, tasks):
    name, domain, spacing, d, block = CASES[1]
    want = seams.seam_arrays(domain, spacing, d, block_points=block)
    cols = [want["x"][:, 0], want["x"][:, 1], *(want[c] for c in seams.POINT)]
    got = seams.fill_seams(spark, domain, spacing, d, block_points=block, tasks=tasks).select("x0", "x1", *seams.POINT).collect()
    assert sorted(map(tuple, got)) == sorted(zip(*(c.tolist() for c in cols), strict=True))


def test_homes_hold_all_candidates():
    """Around any place one zone holds the whole ball of a candidate's reach, and zones of a family are apart."""
    rng = np.random.default_rng(3)
    for d in (1, 2, 3):
        z = seams.Zones(S.Constant(200_000), d, 4000)
        x = rng.integers(0, 1 << 24, (4000, d))
        home, family = z.home(x)
        for p in range(d + 1):
            mine = x[family == p]
            for _ in range(4):
                step = rng.normal(size=mine.shape)
                there = mine + np.rint(step / np.sqrt((step**2).sum(axis=1, keepdims=True)) * (z.reach - 4)).astype(np.int64)
                ok = ((there >= 0) & (there < 1 << 24)).all(axis=1)
                assert (z.holder(there[ok], p) == home[family == p][ok]).all()


def test_seams_raise_at_their_bound():
    with pytest.raises(RuntimeError, match="did not finish"):
        seams.seam_arrays(*CASES[0][1:3], max_stages=1, block_points=600)


def test_border_seeds():
    box = fill.seeds_box((0, 10), (100, 50), 20)
    assert len(box) == len(set(box)) and all(x in (0, 100) or y in (10, 50) for x, y in box) and {(0, 10), (100, 50), (0, 50)} <= set(box)
    line = fill.seeds_polygon(((0, 0), (90, 0), (0, 120)), 30)
    assert line[:3] == [(0, 0), (30, 0), (60, 0)] and len(line) == 3 + 5 + 4


def test_gap_widths_on_a_row():
    row = [np.array([c for c in (i - 1, i + 1) if 0 <= c < 9]) for i in range(9)]
    assert claims.gap_widths(row, np.array([0, 0, -1, 1, 1, -1, -1, 2, -1])).tolist() == [1, 2, 2]
    assert claims.gap_widths(row, np.array([0, -1, -2, -1, 1, 1, 1, 1, 1])).tolist() == []
