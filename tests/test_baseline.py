"""The region-locked baseline in bounded calls and in a task."""

import numpy as np

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.plans import baselines, workloads


def test_region_search_takes_some_points_at_a_time(monkeypatch):
    from frontfill.functions.kernel import Grid

    gens = np.array([[8_388_608, 8_388_608], [6_000_000, 8_000_000], [10_000_000, 9_000_000]], np.int64)
    whole = baselines.voronoi_kd_arrays(D.disc(), S.Constant(400_000), gens)
    monkeypatch.setattr(baselines, "OWNED_AT_ONCE", 7)
    near, most = Grid.near, []

    def watched(self, x, rings):
        if self.side > 400_000:
            most.append(len(x))
        return near(self, x, rings)

    monkeypatch.setattr(Grid, "near", watched)
    some = baselines.voronoi_kd_arrays(D.disc(), S.Constant(400_000), gens)
    assert max(most) <= 7
    assert all(np.array_equal(whole[k], some[k]) for k in whole)


def test_locks_of_the_baseline_are_counted_in_a_task(spark, monkeypatch):
    def on_the_driver(*_a, **_k):
        raise AssertionError("filled on the driver")

    monkeypatch.setattr(baselines, "voronoi_kd_arrays", on_the_driver)
    got = {r.method: r for r in workloads.locks(spark, 300, 3, 32).collect()}
    assert got["voronoi_kd"].exclusive == got["voronoi_kd"].n > 200


def _coarse(h):
    from frontfill.functions.directions import directions
    from frontfill.functions.kernel import front_fill
    from frontfill.functions.lattice import CENTRE

    at, coarse = np.array([[CENTRE, CENTRE]], np.int64), S.Constant(h)
    return np.concatenate([at, front_fill(at, np.arange(1), coarse.at, D.disc().mask, directions(2), h).x])


def test_generators_are_sought_once_a_point(monkeypatch):
    from frontfill.functions.kernel import Grid

    gens = _coarse(1_200_000)
    near, sought = Grid.near, []

    def watched(self, x, rings=1):
        if self.side > 200_000:
            sought.append(len(x))
        return near(self, x, rings)

    monkeypatch.setattr(Grid, "near", watched)
    out = baselines.voronoi_kd_arrays(D.disc(), S.Constant(200_000), gens)
    assert len(out["x"]) > 1000
    # a point has twelve candidates; those near the border may be sought alone
    assert sum(sought) < 3 * len(out["x"])


def test_region_is_that_of_the_nearest_generator(monkeypatch):
    # one generator more, close to another, lies in many balls; the last two stand alone in a corner
    gens = np.concatenate([_coarse(1_500_000), [[8_388_700, 8_388_608], [4_500_000, 4_500_000]]])
    whole = baselines.voronoi_kd_arrays(D.disc(), S.Constant(150_000), gens[:-2])
    every = ((whole["x"][:, None] - gens[None, :-2]) ** 2).sum(axis=2)
    assert np.array_equal(whole["region"], every.argmin(axis=1))
    # with cells too narrow for a parent's list each candidate is sought by itself, and all cuts give the same points
    crowded = baselines.voronoi_kd_arrays(D.disc(), S.Constant(150_000), gens)
    monkeypatch.setattr(baselines, "OWNED_AT_ONCE", 13)
    monkeypatch.setattr(baselines, "PAIRS_AT_ONCE", 40)
    for g, want in ((gens[:-2], whole), (gens, crowded)):
        some = baselines.voronoi_kd_arrays(D.disc(), S.Constant(150_000), g)
        assert all(np.array_equal(want[k], some[k]) for k in want)


def test_report_reads_one_fill(spark, small):
    from frontfill.catalog import claiming

    df = claiming.q42_voronoi_fill_report(spark, small)
    assert "MapInArrow" not in df._jdf.queryExecution().optimizedPlan().toString()
    assert tuple(df.first()) == (0, 0, 0)
