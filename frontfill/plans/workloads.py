"""The experiment workloads W0-W12, each a function that returns a DataFrame of measures.

Numbers of workers are simulated by supersteps (exact counts of claims, stages and idle time); wall-clock figures come from real cores
and are run by ``experiments.py``, not registered as queries, because they differ from run to run.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.lattice import CENTRE, RADIUS, size_h
from frontfill.operators import tree
from frontfill.plans import baselines, claims, coordinated, fill
from frontfill.sources import tables as T
from frontfill.sources.store import stored

XY = ["x0", "x1"]


def w0_density(spark, sizes=(78, 279, 770, 4468)) -> DataFrame:
    """Points of a fill over area / h^2, the constant of the point estimate, by size."""
    rows = []
    for n in sizes:
        h = size_h(n)
        got = fill.fill_sequential(spark, D.disc(), S.Constant(h), fill.seeds_frame(spark, [(CENTRE, CENTRE)])).count()
        rows.append((n, h, got, got * float(h) ** 2 / (3.141592653589793 * float(RADIUS) ** 2)))
    return spark.createDataFrame(rows, "target long, h long, n long, density double")


def w1_snapshot(spark, step: int = 60, h: int = RADIUS // 100, workers: int = 7, limit: int = 100) -> DataFrame:
    """Owner and points of each cell at one superstep of the first stage."""
    pts = claims.fill_claims(spark, D.disc(), S.Constant(h), workers, limit)
    return pts.where(F.col("step") <= step).groupBy("cell").agg(F.count("*").alias("n"), F.mode("worker", True).alias("owner"), F.countDistinct("worker").alias("workers"))


def w2_limits(spark, n: int, workers=(8, 16, 32, 64), limits=(32, 50, 100, 200, 500, 1000, 5000), realisations: int = 5) -> DataFrame:
    """Claims, stages and activity over the work-cell limit."""
    h = size_h(n)
    return claims.sweep(spark, [{"h": h, "limit": x, "workers": w, "realisation": r} for x in limits for w in workers for r in range(realisations)], D.disc())


def w3_scaling(spark, sizes, workers=(1, 2, 4, 8, 16, 32, 64, 128, 256), realisations: int = 3, limit: int = 100) -> DataFrame:
    """Strong scaling of the claiming fill in supersteps: W4 (stage share) and W5 (activity) read the same rows."""
    return claims.sweep(spark, [{"h": size_h(n), "limit": limit, "workers": w, "realisation": r} for n in sizes for w in workers for r in range(realisations)], D.disc())


def w4_stage_share(runs: DataFrame) -> DataFrame:
    return runs.groupBy("h", "workers").agg(F.avg(F.col("stage1_points") / F.col("n")).alias("points"), F.avg(F.col("stage1_steps") / F.col("supersteps")).alias("steps"))


def w5_activity(runs: DataFrame) -> DataFrame:
    return runs.groupBy("h", "workers").agg(F.avg("active").alias("active"), F.min("active").alias("least"), F.max("active").alias("most"))


def w6_prebuild(spark, n: int, limit: int = 100) -> DataFrame:
    """Seconds for tree, levels and seeds against seconds of the fill."""
    h = size_h(n)
    t0 = time.perf_counter()
    cells = stored(tree.spatial_levels(tree.uniform(spark, tree.uniform_level(limit, h, 2), 2), 2))
    t1 = time.perf_counter()
    got = fill.fill_phased(spark, D.disc(), S.Constant(h), limit=limit, one_task=True).count()
    t2 = time.perf_counter()
    return spark.createDataFrame([(got, cells.count(), t1 - t0, t2 - t1, (t1 - t0) / (t2 - t1))], "n long, cells long, prebuild_s double, fill_s double, share double")


def w7_bifurcation(runs: DataFrame) -> DataFrame:
    """Two-cluster split of the efficiencies of single realisations (work over workers and supersteps)."""
    from frontfill.operators.runlog import bifurcation

    return bifurcation(runs.select("run", "method", "h", "workers", F.col("n"), (F.col("supersteps") * F.col("workers")).alias("fill_s")))


def w8_seeds(spark, workers: int) -> DataFrame:
    """One relaxed seed a worker: the number is exact."""
    return fill.seeds_frame(spark, fill.seeds_relaxed(D.disc(), workers))


def histogram_spacing(cloud: DataFrame, level: int = 3, least: int = 150_000, most: int = 450_000) -> S.FromCells:
    """Spacing by cell from the rows of a cloud: dense cells get small spacings.  A row a cell of a fixed level reaches the driver."""
    n = {r["cell"]: r["n"] for r in cloud.groupBy(tree.point_key(XY, level).alias("cell")).agg(F.count("*").alias("n")).collect()}
    top = max(n.values(), default=1)
    return S.FromCells(level, {c: int(max(least, min(most, least * (top / v) ** 0.5))) for c, v in n.items()}, most)


def w9_variable(spark, cloud: DataFrame, limit: int = 200) -> DataFrame:
    """An adaptive balanced tree and a phased fill with spacing from a table's density."""
    return w9_points(spark, histogram_spacing(cloud), limit).groupBy("stage").agg(F.count("*").alias("n"), F.min("h").alias("least"), F.max("h").alias("most"))


def w9_points(spark, sp: S.Spacing, limit: int = 200) -> DataFrame:
    """The points of that fill."""
    cells = stored(tree.balance(tree.build_estimated(spark, sp, 2, limit, deepest=5), 2))
    return fill.fill_phased(spark, D.disc(), sp, cells=cells, one_task=True)


def w10_distributed(spark, workers: int, n: int, quantum: int = 200) -> DataFrame:
    """The coordinated mode: points and rounds by worker."""
    pts = coordinated.fill_coordinated(spark, D.disc(), S.Constant(size_h(n)), fill.seeds_relaxed(D.disc(), workers), quantum=quantum)
    return pts.groupBy("worker").agg(F.count("*").alias("n"), F.max("round").alias("rounds"))


def w11_rediscretise(spark, week1: DataFrame, week2: DataFrame) -> DataFrame:
    """Refill after the density moves from one week's rows to the next's."""
    return w11_points(spark, histogram_spacing(week1), histogram_spacing(week2))[1].groupBy("kept").agg(F.count("*").alias("n"))


def w11_points(spark, old: S.Spacing, new: S.Spacing) -> tuple[DataFrame, DataFrame]:
    """The points before and after the change."""
    pts = stored(fill.fill_sequential(spark, D.disc(), old, fill.seeds_frame(spark, [(CENTRE, CENTRE)])))
    return pts, stored(coordinated.refill(pts, XY, D.disc(), old, new, level=3))


def costly_disc(corners: int = 720) -> D.Domain:
    """The disc as a polygon of many edges: a membership test that costs far more."""
    a = np.linspace(0, 2 * np.pi, corners, endpoint=False)
    return D.Polygon(tuple((int(round(CENTRE + RADIUS * np.cos(t))), int(round(CENTRE + RADIUS * np.sin(t)))) for t in a))


def w12_membership(spark, n: int) -> DataFrame:
    """Seconds of method and baseline on a cheap and a costly membership test of one shape."""
    rows = []
    h = S.Constant(size_h(n))
    for name, dom in (("disc", D.disc()), ("polygon", costly_disc())):
        for method, run in (("phased", lambda dom=dom: fill.fill_phased(spark, dom, h, one_task=True)), ("voronoi_kd", lambda dom=dom: baselines.voronoi_kd_fill(spark, dom, h))):
            t = time.perf_counter()
            k = run().count()
            rows.append((name, method, k, time.perf_counter() - t))
    return spark.createDataFrame(rows, "shape string, method string, n long, seconds double")


def locks(spark, n: int, workers: int = 7, limit: int = 100, leaf: int = 40) -> DataFrame:
    """Synchronisation events for each insert: claims (M10), region locks (B2), leaf locks."""
    h = size_h(n)
    r = claims.sweep(spark, [{"h": h, "limit": limit, "workers": workers}], D.disc()).first()
    v = baselines.voronoi_kd_locks(spark, D.disc(), S.Constant(h)).first()
    pts = stored(fill.fill_phased(spark, D.disc(), S.Constant(h), limit=limit, one_task=True).withColumn("id", F.xxhash64(*XY)))
    lk = baselines.leaf_lock_counts(pts, tree.build_counted(pts, leaf, 10, names=XY), XY, h).first()
    rows = [("claims", r["n"], r["attempts"], r["releases"] + r["entries"]), ("voronoi_kd", v["n"], v["writes"], v["reads"]), ("leaf_lock", pts.count(), lk["exclusive"], lk["shared"])]
    return spark.createDataFrame([(m, n_, e, s, e / n_, s / n_) for m, n_, e, s in rows], "method string, n long, exclusive long, other long, exclusive_per_insert double, other_per_insert double")


def week(spark, sf, k: int) -> DataFrame:
    """Events of one week of the month."""
    e = T.table(spark, sf, "events")
    lo = 1_704_067_200 + 7 * 86_400 * k
    return T.events_axes(e.where((F.unix_timestamp(F.col("ts").cast("timestamp")) >= lo) & (F.unix_timestamp(F.col("ts").cast("timestamp")) < lo + 7 * 86_400)))
