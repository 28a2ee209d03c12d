"""Separation of vectors by blocks; nearest rows by cells of fitting size."""

import numpy as np
import pytest

from frontfill.operators import measures


@pytest.mark.parametrize("most", [3, 7, 16_384])
def test_separation_by_blocks(spark, most):
    rng = np.random.default_rng(3)
    odd = [(None, [0.0, 0.0]), (50, None), (51, [0.0, None]), (52, [0.1]), (53, [0.1]), (54, [float("nan"), 0.0]), (7, [0.2, 0.2]), (7, [0.2, 0.2])]
    rows = [(i, rng.uniform(-1, 1, 2).round(2).tolist()) for i in range(40)] + odd
    whole = [(i, v) for i, v in rows if i is not None and v is not None and None not in v]
    want = sorted((a, b) for a, v in whole for b, w in whole if a < b and len(v) == len(w) and sum((x - y) ** 2 for x, y in zip(v, w)) ** 0.5 < 0.5)
    df = measures.separation(spark.createDataFrame(rows, "id long, vec array<double>"), 0.5, most)
    assert sorted((r.a, r.b) for r in df.collect()) == want
    assert "Join" not in df._jdf.queryExecution().executedPlan().toString()


def test_nearest_of_crowded_and_odd_rows(spark, monkeypatch):
    rng = np.random.default_rng(5)
    rows = [(i, *rng.integers(0, 3000, 2).tolist()) for i in range(600)] + [(1000 + i, *rng.integers(0, 200_000, 2).tolist()) for i in range(60)]
    rows += [(2000, 5, 5), (2001, 5, 5), (2002, 900_000, 900_000), (2002, 900_000, 900_000), (2003, 900_500, 900_000), (2004, 700_000, 0), (7, 800_000, 0), (None, 800_001, 0), (2005, None, 0)]
    made = []
    pairs = measures.within_pairs
    monkeypatch.setattr(measures, "within_pairs", lambda *a: made.append(out := pairs(*a)) or out)
    got = measures.nearest(spark.createDataFrame(rows, "id long, x0 long, x1 long"), ["x0", "x1"], 60_000).collect()
    assert len(got) == len(rows)
    real = [r for r in rows if None not in r]
    want = {i: min((g for j, x, y in real for k, v, w in real if k == i != j and (g := (x - v) ** 2 + (y - w) ** 2) < 60_000**2), default=None) for i, *_ in real}
    assert all(r.d2 == want.get(r.id) for r in got)
    assert sum(m.count() for m in made) < 100 * len(rows)
