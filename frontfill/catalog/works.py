"""Queries of the experiment workloads: behaviours that must hold, on sizes taken from the tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from frontfill.functions import domain as D
from frontfill.functions.lattice import size_h
from frontfill.operators import measures, rows, tree
from frontfill.plans import workloads as W
from frontfill.sources import tables as T
from frontfill.sources.store import stored


def _n(spark, sf, t):
    return T.table(spark, sf, t).count()


def w0_density(spark, sf):
    """The density constant falls towards its limit as the border matters less."""
    r = W.w0_density(spark, (_n(spark, sf, "supplier"), 279, 1000 + _n(spark, sf, "customer")))
    return r.agg(F.count("*").alias("sizes"), (F.min("density") > 0.8).alias("dense"), (F.max("density") < 1.3).alias("bounded"))


def w1_snapshot(spark, sf):
    """Seven workers near the end of stage one: all hold cells."""
    return W.w1_snapshot(spark, 60, size_h(4 * _n(spark, sf, "customer"))).agg(F.countDistinct("owner").alias("owners"), (F.count("*") > 20).alias("cells"))


def w2_limits(spark, sf):
    """Smaller cells mean more claims; every run ends complete."""
    r = stored(W.w2_limits(spark, 4 * _n(spark, sf, "customer"), (8,), (32, 500), 2))
    by = r.groupBy().pivot("lim", [32, 500]).agg(F.avg("grants"))
    return r.agg(F.count("*").alias("runs"), F.sum("unexpanded").alias("unexpanded"), F.sum("owners_clash").alias("clashes")).crossJoin(by.select((F.col("32") > F.col("500")).alias("more_claims")))


def w3_scaling(spark, sf):
    """Activity falls as workers grow, and rises with the size at equal workers; stage one holds most points."""
    n = 2 * _n(spark, sf, "customer")
    r = stored(W.w3_scaling(spark, (n, 8 * n), (1, 8, 32), 2))
    a = W.w5_activity(r).groupBy("h").pivot("workers", [1, 8, 32]).agg(F.first("active"))
    lo = a.agg(F.min_by("8", "h").alias("large"), F.max_by("8", "h").alias("small"), (F.min(F.col("1") - F.col("32")) > 0).alias("falls"))
    s = W.w4_stage_share(r).agg((F.min("points") > 0.5).alias("mostly_first"))
    return r.agg(F.count("*").alias("runs"), F.sum("unexpanded").alias("unexpanded")).crossJoin(lo.select("falls", (F.col("large") > F.col("small")).alias("rises"))).crossJoin(s)


def w6_prebuild(spark, sf):
    """Prebuild against fill: both were done, and as many cells as the level has."""
    n = max(1500, _n(spark, sf, "customer"))
    r = W.w6_prebuild(spark, n)
    cells = 4 ** tree.uniform_level(100, size_h(n), 2)
    return r.select((F.col("cells") == cells).alias("cells"), F.col("n").between(n * 0.9, n * 1.1).alias("filled"), (F.col("share") > 0).alias("measured"))


def w7_bifurcation(spark, sf):
    """Clusters of single runs: each run is in one of two, and the better one's mean is no lower."""
    r = stored(W.w3_scaling(spark, (2 * _n(spark, sf, "customer"),), (8,), 6))
    b = W.w7_bifurcation(r)
    return b.select(F.col("workers").cast("long").alias("workers"), (F.col("in_low") + F.col("in_high")).alias("runs"), (F.col("ratio") >= 1).alias("apart"))


def w9_variable(spark, sf):
    """Variable spacing from the orders' density: no violation, nothing open, spacing within its bounds and smaller where orders are dense."""
    sp = W.histogram_spacing(T.orders(spark, sf))
    pts = stored(W.w9_points(spark, sp).withColumn("ord", F.struct("stage", "phase", "rank", "seq")))
    bad = measures.violations(pts.select("ord", "h_parent", *W.XY), W.XY, sp.most).agg(F.count("*").alias("violations"))
    free = measures.open_candidates(pts.select(*W.XY, "h"), D.disc(), 2, sp.most).agg(F.count("*").alias("open"))
    wrong = pts.agg(F.sum((F.col("h") != sp.column(W.XY)).cast("long")).alias("other_spacing"), (F.min("h") >= 150_000).alias("low"), (F.max("h") <= 450_000).alias("high"))
    return bad.crossJoin(free).crossJoin(wrong)


def w11_rediscretise(spark, sf):
    """Refilling from week one to week two: kept points are old ones with the same spacing, new ones keep their distance, nothing stays open."""
    old, new = (W.histogram_spacing(W.week(spark, sf, k)) for k in (0, 1))
    before, after = W.w11_points(spark, old, new)
    same = before.where(old.column(W.XY) == new.column(W.XY)).select(*W.XY)
    kept = after.where("kept").select(*W.XY)
    lost = same.exceptAll(kept).unionByName(kept.exceptAll(before.select(*W.XY))).agg(F.count("*").alias("lost"))
    close = rows.within_pairs(after.where("not kept").select(*W.XY), after.select(*W.XY), W.XY, new.most, F.lit(new.least).cast("long")).where("a_x0 <> b_x0 or a_x1 <> b_x1").agg(F.count("*").alias("too_close"))
    free = measures.open_candidates(after.select(*W.XY, new.column(W.XY).alias("h")), D.disc(), 2, new.most).agg(F.count("*").alias("open"))
    return lost.crossJoin(close).crossJoin(free)


def w12_membership(spark, sf):
    """A costly membership test changes the time, not the points: fills of the disc and of its polygon are as large for either method."""
    r = stored(W.w12_membership(spark, max(1500, _n(spark, sf, "customer"))))
    by = r.groupBy("method").agg(F.count("*").alias("shapes"), (F.max("n") <= 1.05 * F.min("n")).alias("alike"), (F.min("seconds") > 0).alias("timed"))
    return by


def w_locks(spark, sf):
    """The claims of the method are far fewer for each insert than the locks of both baselines."""
    r = W.locks(spark, 8 * _n(spark, sf, "customer"))
    p = r.groupBy().pivot("method", ["claims", "voronoi_kd", "leaf_lock"]).agg(F.first("exclusive_per_insert"))
    return p.select((F.col("claims") < 0.2 * F.col("voronoi_kd")).alias("under_region_locks"), (F.col("claims") < 0.2 * F.col("leaf_lock")).alias("under_leaf_locks"))


QUERIES = {n: f for n, f in list(globals().items()) if n.startswith("w") and callable(f) and f.__module__ == __name__}
ORACLES = {
    "w0_density": "SELECT 3::BIGINT AS sizes, true AS dense, true AS bounded",
    "w1_snapshot": "SELECT 7::BIGINT AS owners, true AS cells",
    "w2_limits": "SELECT 4::BIGINT AS runs, 0::BIGINT AS unexpanded, 0::BIGINT AS clashes, true AS more_claims",
    "w3_scaling": "SELECT 12::BIGINT AS runs, 0::BIGINT AS unexpanded, true AS falls, true AS rises, true AS mostly_first",
    "w6_prebuild": "SELECT true AS cells, true AS filled, true AS measured",
    "w7_bifurcation": "SELECT 8::BIGINT AS workers, 6::BIGINT AS runs, true AS apart",
    "w9_variable": "SELECT 0::BIGINT AS violations, 0::BIGINT AS open, 0::BIGINT AS other_spacing, true AS low, true AS high",
    "w11_rediscretise": "SELECT 0::BIGINT AS lost, 0::BIGINT AS too_close, 0::BIGINT AS open",
    "w12_membership": "SELECT method, 2::BIGINT AS shapes, true AS alike, true AS timed FROM (VALUES ('phased'), ('voronoi_kd')) t(method)",
    "w_locks": "SELECT true AS under_region_locks, true AS under_leaf_locks",
}
