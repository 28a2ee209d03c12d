"""Refilling after a change of the spacing: nothing kept is lost, no two are too near, no candidate stays open."""

import numpy as np
import pytest

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.directions import directions, propose
from frontfill.functions.kernel import Grid
from frontfill.functions.lattice import CENTRE
from frontfill.plans import coordinated, fill

H = 400_000
XY = ["x0", "x1"]
TWO = D.Box((500_000, 500_000), (6_000_000, 6_000_000)) | D.Box((9_100_000, 9_100_000), (9_900_000, 9_900_000))
CASES = {
    "half": (D.disc(), S.Step(0, CENTRE, H, H // 2)),
    "coarser": (D.disc(), S.Step(0, CENTRE, H, 2 * H)),
    "everywhere": (D.disc(), S.Constant(H // 2)),
    "apart": (TWO, S.Step(0, CENTRE, H, H // 2)),
}


@pytest.mark.parametrize("how", ["refill", "refill_sequential"])
@pytest.mark.parametrize("case", CASES)
def test_refill_is_whole(spark, case, how):
    dom, new = CASES[case]
    old = S.Constant(H)
    seeds = fill.seeds_frame(spark, [(3_000_000, 3_000_000), (9_500_000, 9_500_000)] if case == "apart" else [(CENTRE, CENTRE)])
    pts = fill.fill_sequential(spark, dom, old, seeds)
    before = {(r.x0, r.x1) for r in pts.select(*XY).collect()}
    got = getattr(coordinated, how)(pts, XY, dom, old, new).collect()
    x = np.array([(r.x0, r.x1) for r in got], np.int64)
    kept = np.array([r.kept for r in got])
    assert len({tuple(p) for p in x.tolist()}) == len(x) and dom.mask(x).all()
    still = {p for p in before if old.at(np.array([p]))[0] == new.at(np.array([p]))[0]}
    assert {tuple(p) for p in x[kept].tolist()} == still
    gap = ((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2)
    np.fill_diagonal(gap, 1 << 60)
    assert (gap[~kept] >= new.least**2).all()
    cand = propose(x, new.at(x), directions(2, None), False)
    radius = np.repeat(new.at(x), cand.shape[1])
    cand = cand.reshape(-1, 2)
    inside = dom.mask(cand)
    cand, radius = cand[inside], radius[inside]
    near = np.concatenate([((c[:, None, :] - x[None, :, :]) ** 2).sum(axis=2).min(axis=1) for c in np.array_split(cand, 50)])
    assert (near < radius**2).all()
    # each part that had points has some again
    for lo, hi in ((0, CENTRE), (CENTRE, 1 << 24)):
        if any(lo <= p[0] < hi for p in before):
            assert ((x[:, 0] >= lo) & (x[:, 0] < hi)).any()


def test_refill_by_blocks_is_whole(spark):
    """Many blocks: kept points on both sides of seams."""
    old, new = S.Constant(100_000), S.Step(0, CENTRE, 100_000, 60_000)
    pts = fill.fill_sequential(spark, D.disc(), old, fill.seeds_frame(spark, [(CENTRE, CENTRE)]))
    x0 = np.array([(r.x0, r.x1) for r in pts.select(*XY).collect()], np.int64)
    out = coordinated.refill(pts, XY, D.disc(), old, new, block_points=400)
    assert out.rdd.getNumPartitions() > 1
    got = out.collect()
    x = np.array([(r.x0, r.x1) for r in got], np.int64)
    kept = np.array([r.kept for r in got])
    assert len(np.unique(x, axis=0)) == len(x) and D.disc().mask(x).all()
    assert {tuple(p) for p in x[kept].tolist()} == {tuple(p) for p in x0[x0[:, 0] < CENTRE].tolist()}
    grid = Grid(2, new.most)
    grid.add(x, 0)
    a, b = grid.near(x[~kept], 1)
    gap = ((x[~kept][a] - x[b]) ** 2).sum(axis=1)
    assert (gap[gap > 0] >= new.least**2).all()
    cand = propose(x, new.at(x), directions(2, None), False)
    radius = np.repeat(new.at(x), cand.shape[1])
    cand = cand.reshape(-1, 2)
    inside = D.disc().mask(cand)
    cand, radius = cand[inside], radius[inside]
    q, j = grid.near(cand, 1)
    free = np.ones(len(cand), bool)
    free[q[((cand[q] - x[j]) ** 2).sum(axis=1) < radius[q] ** 2]] = False
    assert not free.any()
