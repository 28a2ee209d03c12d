import numpy as np
import pytest

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.directions import directions, propose
from frontfill.functions.kernel import front_fill
from frontfill.functions.lattice import CENTRE, SIDE, key_array, morton, size_h, spread
from frontfill.operators.tree import Leaves
from frontfill.plans import claims, fill


def one_by_one(x, sp, dom, dirs, annulus=False):
    """The fill by its definition: one candidate at a time against all accepted points."""
    pts, head = [tuple(p) for p in x], 0
    while head < len(pts):
        p = np.array([pts[head]])
        h = int(sp.at(p)[0])
        for c in propose(p, np.array([h]), dirs, annulus)[0]:
            if dom.mask(c[None])[0] and (((np.array(pts) - c) ** 2).sum(axis=1) >= h * h).all():
                pts.append(tuple(int(v) for v in c))
        head += 1
    return pts


CASES = [
    (D.disc(), S.Constant(600_000), 2, False),
    (D.disc(), S.Constant(900_000), 2, True),
    (D.disc(d=3), S.Constant(1_800_000), 3, False),
    (D.Box((0,), (9_000_000,)), S.Constant(333_333), 1, False),
    (D.disc(), S.Linear(300_000, 1_500_000), 2, False),
    (D.annulus((CENTRE, CENTRE), 3_000_000, 6_000_000), S.Step(1, CENTRE, 500_000, 900_000), 2, False),
    (D.disc(), S.Radial((CENTRE, CENTRE), 300_000, 900_000, 6_000_000), 2, False),
]


@pytest.mark.parametrize("dom,sp,d,annulus", CASES)
def test_kernel_is_the_one_by_one_fill(dom, sp, d, annulus):
    start = np.full((1, d), CENTRE)
    if not dom.mask(start)[0]:
        start[0, 0] += 4_000_000
    dirs = directions(d)
    f = front_fill(start, np.arange(1), sp.at, dom.mask, dirs, sp.most, annulus=annulus)
    got = [tuple(p) for p in np.concatenate([start, f.x]).tolist()]
    assert got == one_by_one(start.tolist(), sp, dom, dirs, annulus)
    assert len(got) > 15


@pytest.mark.parametrize("order", ["lifo", "random"])
def test_other_queue_orders_still_fill(order):
    sp, dom, dirs = S.Constant(700_000), D.disc(), directions(2)
    start = np.array([[CENTRE, CENTRE]])
    f = front_fill(start, np.arange(1), sp.at, dom.mask, dirs, sp.most, order=order)
    x = np.concatenate([start, f.x])
    gap = ((x[:, None] - x[None]) ** 2).sum(axis=2) + np.eye(len(x), dtype=np.int64) * 10**15
    assert gap.min() >= 700_000**2
    cand = propose(x, sp.at(x), dirs).reshape(-1, 2)
    cand = cand[dom.mask(cand)]
    assert (((cand[:, None] - x[None]) ** 2).sum(axis=2).min(axis=1) < 700_000**2).all()


def test_candidates_keep_their_distance_from_the_parent():
    rng = np.random.default_rng(1)
    for d in (1, 2, 3, 4):
        x = rng.integers(2**22, 2**23, (200, d))
        h = rng.integers(4, 5_000_000, 200)
        c = propose(x, h, directions(d))
        assert (((c - x[:, None]) ** 2).sum(axis=2) >= (h**2)[:, None]).all()


def test_morton():
    rng = np.random.default_rng(2)
    for d, bits in ((1, 20), (2, 24), (3, 20), (4, 15)):
        c = [rng.integers(0, 1 << bits, 50) for _ in range(d)]
        got = morton(c, bits)
        for i in range(50):
            want = sum(((int(c[a][i]) >> b) & 1) << (d * b + d - 1 - a) for b in range(bits) for a in range(d))
            assert got[i] == want
    assert spread(np.array([0b101]), 2, 24)[0] == 0b10001
    assert key_array([np.array([1]), np.array([0])], 1)[0] == 6


def violated(p, h):
    x = p["x"]
    gap = ((x[:, None] - x[None]) ** 2).sum(axis=2) + np.eye(len(x), dtype=np.int64) * 10**15
    return int((gap < h * h).sum())


@pytest.mark.parametrize("level,n", [(2, 300), (3, 400), (3, 100)])
def test_phased_arrays_hold_the_spacing(level, n):
    h = size_h(n)
    p = fill.phased_arrays(Leaves.uniform(level, 2), D.disc(), S.Constant(h))
    wide = (SIDE >> level) >= 3 * h + 6
    assert (violated(p, h) == 0) or not wide
    assert wide == (n != 100)


def test_phased_needs_no_particular_tasks(spark):
    h = S.Constant(size_h(900))
    key = ["x0", "x1", "cell", "by_cell", "stage", "phase", "seq"]
    runs = [sorted(map(tuple, fill.fill_phased(spark, D.disc(), h, limit=32, one_task=b, cells_per_task=c).select(*key).collect())) for b, c in ((True, None), (False, 1), (False, 5), (False, None))]
    assert all(r == runs[0] for r in runs) and len(runs[0]) > 700


def test_edges_of_the_domain(spark):
    sp = S.Constant(size_h(200))
    none = fill.fill_sequential(spark, D.disc(), sp, fill.seeds_frame(spark, []))
    assert none.count() == 0
    out = fill.fill_sequential(spark, D.disc(), sp, fill.seeds_frame(spark, [(1, 1)]))
    assert out.count() == 0
    twice = fill.fill_sequential(spark, D.disc(), sp, fill.seeds_frame(spark, [(CENTRE, CENTRE)] * 2))
    assert twice.count() == fill.fill_sequential(spark, D.disc(), sp, fill.seeds_frame(spark, [(CENTRE, CENTRE)])).count()
    big = fill.fill_sequential(spark, D.disc(500_000), S.Constant(3_000_000), fill.seeds_frame(spark, [(CENTRE, CENTRE)]))
    assert big.count() == 1
    # two discs apart: only the seeded one fills, unless each cell has a seed
    two = D.Ball((4_000_000, CENTRE), 1_500_000) | D.Ball((12_000_000, CENTRE), 1_500_000)
    one = fill.fill_sequential(spark, two, S.Constant(300_000), fill.seeds_frame(spark, [(4_000_000, CENTRE)]))
    assert one.where("x0 > 8000000").count() == 0
    assert fill.fill_phased(spark, two, S.Constant(300_000), limit=40, one_task=True).where("x0 > 8000000").count() > 20


@pytest.mark.parametrize("workers,quantum,order,seek", [(1, 64, "fifo", "none"), (7, 8, "shuffled", "none"), (12, 16, "fifo", "enqueued"), (40, 4, "shuffled", "far")])
def test_claims_end_complete(workers, quantum, order, seek):
    h = size_h(1500)
    r = claims.simulate(Leaves.uniform(3, 2), D.disc(), S.Constant(h), fill.seeds_relaxed(D.disc(), workers), quantum, order, seek=seek)
    assert r.owners_clash == 0 and r.unexpanded == 0 and r.left_in_set == 0
    assert violated({"x": r.x}, h) == 0
    cand = propose(r.x, np.full(len(r.x), h), directions(2)).reshape(-1, 2)
    cand = cand[D.disc().mask(cand)]
    assert (((cand[:, None] - r.x[None]) ** 2).sum(axis=2).min(axis=1) < h * h).all()
    assert workers > 1 or r.counts["fails"] == 0


def test_narrow_cells_break_the_spacing_and_repair_mends_it(spark):
    """With cells under three spacings the seams clash; this is what the width guard is for."""
    from frontfill.operators.measures import violations
    from frontfill.plans.coordinated import repair

    h = size_h(900)
    leaves = Leaves.uniform(5, 2)
    p = fill.phased_arrays(leaves, D.disc(), S.Constant(h))
    x = p["x"]
    df = spark.createDataFrame([(int(i), int(a), int(b), h) for i, (a, b) in enumerate(x)], "ord long, x0 long, x1 long, h_parent long")
    kept, gone = repair(df, ["x0", "x1"], ["ord"], h)
    assert violations(kept, ["x0", "x1"], h).count() == 0
    assert kept.count() + gone.count() == len(x)
