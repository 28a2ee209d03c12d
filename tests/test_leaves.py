"""Leaves within a reach of points, also where leaves are smaller than the reach."""

from frontfill.operators import rows, tree
from frontfill.plans import baselines

XY = ["x0", "x1"]


def _case(spark):
    # a crowd in one corner makes leaves of 2^14, others are coarse
    at = [(i, (i * 7919) % 300_000, (i * 104_729) % 300_000) for i in range(400)] + [(400 + i, i * 5_000_000, i * 5_500_000) for i in range(4)]
    pts = spark.createDataFrame(at, "id long, x0 long, x1 long")
    cells = tree.build_counted(pts, 4, 10, names=XY)
    return pts, cells, [r for r in tree.with_boxes(cells, 2).collect()], at


def test_leaf_locks_reach_beyond_the_next_leaf(spark):
    pts, cells, boxes, at = _case(spark)
    h = 200_000
    far = lambda v, lo, side: max(0, lo - v, v - (lo + side - 1))
    met = sum(far(x, b.lo0, b.side) ** 2 + far(y, b.lo1, b.side) ** 2 < h * h for _, x, y in at for b in boxes)
    got = baselines.leaf_lock_counts(pts, cells, XY, h).first()
    assert (got.exclusive, got.shared) == (len(at), met)


def test_halo_reaches_beyond_the_next_leaf(spark):
    pts, cells, boxes, at = _case(spark)
    for gap in (100, 200_000, 1 << 24):
        want = {(i, b.cell) for i, x, y in at for b in boxes if all(lo - gap <= v < lo + b.side + gap for v, lo in ((x, b.lo0), (y, b.lo1)))}
        got = [tuple(r) for r in rows.halo(pts, cells, XY, gap).select("id", "target").collect()]
        assert len(got) == len(want) and set(got) == want


def test_merged_tree_broadcasts_nothing(spark, small):
    from frontfill.catalog import trees

    df = trees.q50c_merged_tree(spark, small)
    df.collect()
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "BroadcastExchange" not in plan

def test_pairs_and_open_candidates_merge(spark):
    from frontfill.functions import domain as D
    from frontfill.operators import measures
    from frontfill.operators.rows import within_pairs
    from pyspark.sql import functions as F

    p = spark.createDataFrame([(i, 8_000_000 + i, 8_000_000, 100) for i in range(20)], "id long, x0 long, x1 long, h long")
    for df in (within_pairs(p, p, ["x0", "x1"], 100, F.lit(100)), measures.open_candidates(p, D.disc(), 2, 100)):
        df.collect()
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_leaves_around_points_merge(spark):
    pts, cells, _, at = _case(spark)
    df = baselines.leaf_lock_counts(pts, cells, XY, 200_000)
    assert df.collect()[0].exclusive == len(at)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan
