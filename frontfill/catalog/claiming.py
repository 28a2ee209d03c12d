"""Queries of claims, restarts, baselines with locks, the coordinated mode, repair and refilling."""

from __future__ import annotations


from pyspark.sql import functions as F

from frontfill.catalog import clouds_sql as C
from frontfill.catalog import recursion as R
from frontfill.catalog.rowsets import XY, _RND
from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.lattice import CENTRE, size_h
from frontfill.operators import measures, rows, tree
from frontfill.plans import baselines, claims, coordinated, fill
from frontfill.sources import tables as T


def _n(spark, sf, t):
    return T.table(spark, sf, t).count()


def _report(pts, h, extra=()):
    """Violations, points outside and open candidates of a fill with constant spacing."""
    p = pts.withColumn("h", F.lit(h).cast("long"))
    bad = measures.violations(p.select("ord", "h_parent", *XY), XY, h).agg(F.count("*").alias("violations"))
    out = p.agg(F.sum((~D.disc().column(XY)).cast("long")).alias("outside"), *extra)
    free = measures.open_candidates(p, D.disc(), 2, h).agg(F.count("*").alias("open"))
    return bad.crossJoin(out).crossJoin(free)


def q08b_fill_phased_adaptive(spark, sf):
    """M11 on an adaptive balanced tree (M3b, M3c) with spacing that varies fourfold: no violation, nothing outside, nothing open."""
    h = size_h(_n(spark, sf, "customer"))
    sp = S.Linear(h, 2 * h)
    from frontfill.sources.store import stored

    cells = stored(tree.balance(tree.build_estimated(spark, sp, 2, 60, deepest=5), 2))
    pts = stored(fill.fill_phased(spark, D.disc(), sp, cells=cells, one_task=True).withColumn("ord", F.struct("stage", "phase", "rank", "seq")))
    bad = measures.violations(pts.select("ord", "h_parent", *XY), XY, sp.most).agg(F.count("*").alias("violations"))
    out = pts.agg(F.sum((~D.disc().column(XY)).cast("long")).alias("outside"), (F.count("*") > 100).alias("filled"))
    free = measures.open_candidates(pts.select(*XY, "h"), D.disc(), 2, sp.most).agg(F.count("*").alias("open"))
    narrow = tree.check_width(cells, sp, 2).agg(F.count("*").alias("narrow"))
    return bad.crossJoin(out).crossJoin(free).crossJoin(narrow)


Q08B = "SELECT 0::BIGINT AS violations, 0::BIGINT AS outside, true AS filled, 0::BIGINT AS open, 0::BIGINT AS narrow"


def q09_fill_claims_report(spark, sf):
    """M10 with seven workers: A2, A3, A4 and more than one worker at work."""
    h = size_h(_n(spark, sf, "customer"))
    pts = claims.fill_claims(spark, D.disc(), S.Constant(h), 7, limit=32, quantum=16)
    return _report(pts, h, (F.countDistinct("worker").alias("workers"),))


Q09 = "SELECT 0::BIGINT AS violations, 0::BIGINT AS outside, 0::BIGINT AS open, 7::BIGINT AS workers"


def q10_fill_coordinated_report(spark, sf):
    """M12 with a worker a region: the merged set has no violation, nothing outside, nothing open."""
    w = _n(spark, sf, "region")
    h = size_h(60 * w)
    pts = coordinated.fill_coordinated(spark, D.disc(), S.Constant(h), fill.seeds_relaxed(D.disc(), w), quantum=60)
    return _report(pts.withColumn("ord", F.struct("round", "worker", "seq")), h)


Q10 = "SELECT 0::BIGINT AS violations, 0::BIGINT AS outside, 0::BIGINT AS open"


def q11_restart_orders(spark, sf):
    """Both restart orders end with an empty set, no unexpanded point and no neighbouring owners."""
    h = size_h(20 * _n(spark, sf, "supplier"))
    configs = [{"h": h, "limit": 32, "workers": 9, "realisation": r, "quantum": 8, "order": o} for o in ("fifo", "shuffled") for r in range(2)]
    got = claims.sweep(spark, configs, D.disc())
    return got.agg(F.count("*").alias("runs"), F.sum("owners_clash").alias("clashes"), F.sum("unexpanded").alias("unexpanded"), F.sum("left_in_set").alias("left_in_set"))


Q11 = "SELECT 4::BIGINT AS runs, 0::BIGINT AS clashes, 0::BIGINT AS unexpanded, 0::BIGINT AS left_in_set"


def q11b_idle_seeking(spark, sf):
    """Idle workers that seek enqueued or far cells leave nothing undone and are active no less."""
    h = size_h(20 * _n(spark, sf, "supplier"))
    got = claims.sweep(spark, [{"h": h, "limit": 32, "workers": 9, "quantum": 8, "seek": s, "realisation": r} for s in ("none", "enqueued", "far", "unfilled") for r in range(3)], D.disc())
    return got.agg(F.sum("owners_clash").alias("clashes"), F.sum("unexpanded").alias("unexpanded"), F.sum("left_in_set").alias("left_in_set"), F.count("*").alias("runs"))


Q11B = "SELECT 0::BIGINT AS clashes, 0::BIGINT AS unexpanded, 0::BIGINT AS left_in_set, 12::BIGINT AS runs"



def q09c_claims_in_tasks(spark, sf):
    """The claiming fill with a task a worker and superstep has the points, owners and cells of the simulated one."""
    h = size_h(max(500, 5 * _n(spark, sf, "supplier")))
    args = {"workers": 4, "limit": 32, "quantum": 1000}
    one = claims.fill_claims(spark, D.disc(), S.Constant(h), **args).select(*XY, "h_parent", "worker", "cell")
    many = claims.fill_claims_tasks(spark, D.disc(), S.Constant(h), **args).select(*XY, "h_parent", "worker", "cell")
    both = one.withColumn("s", F.lit(1)).unionByName(many.withColumn("s", F.lit(-1))).groupBy(*XY, "h_parent", "worker", "cell").agg(F.sum("s").alias("s"))
    return both.agg(F.sum((F.col("s") != 0).cast("long")).alias("differ"), (F.count("*") > 100).alias("filled"))


Q09C = "SELECT 0::BIGINT AS differ, true AS filled"


def q09b_gap_width(spark, sf):
    """Gaps between dry fronts when the first stage ends are one or two cells wide, but for a few; A20: every candidate is outside, blocked or a point."""
    h = size_h(max(2000, 20 * _n(spark, sf, "supplier")))
    got = claims.sweep(spark, [{"h": h, "limit": 32, "workers": w, "quantum": 8, "realisation": r} for w in (4, 9) for r in range(3)], D.disc())
    return got.agg(
        F.count("*").alias("runs"), (F.sum("gap_one") > 0).alias("one"), (F.sum("gap_two") > 0).alias("two"), (10 * F.sum("gap_wider") <= F.sum(F.col("gap_one") + F.col("gap_two"))).alias("few_wider"),
        F.sum(F.col("tested") - F.col("outside") - F.col("blocked") - F.col("n") + F.col("workers")).alias("unaccounted"),
    )


Q09B = "SELECT 6::BIGINT AS runs, true AS one, true AS two, true AS few_wider, 0::BIGINT AS unaccounted"

LV = 4


def _cells(spark, sf):
    """Full-tree cells of the orders, the nation that asks for each, and links."""
    o = T.orders(spark, sf).select("id", tree.point_key(XY, LV).alias("cell"))
    nodes = o.select("cell").distinct().withColumn("level", F.lit(LV))
    return o, tree.neighbours(nodes, 2)


def _requests(spark, sf, o):
    s = T.table(spark, sf, "supplier").select(F.col("s_suppkey"), F.col("s_nationkey").cast("int").alias("worker"))
    return s.join(o, F.col("id") == F.col("s_suppkey") * 7).select("worker", "cell").distinct()


def _state(o):
    """A synthetic cell state from the first order of each cell."""
    first = o.groupBy("cell").agg(F.min("id").alias("id"))
    st = F.when(F.col("id") % 11 == 0, "claimed").when(F.col("id") % 11 == 1, "failed").when(F.col("id") % 11 == 2, "enqueued").otherwise("idle")
    return first.select("cell", st.alias("state"), F.when(F.col("id") % 11 < 2, F.col("id") % 5).cast("int").alias("owner"), F.when(F.col("id") % 11 == 0, F.col("id") % 2).otherwise(0).cast("int").alias("front_count"))


def q24_claim_round(spark, sf):
    """M6: one arbitration of claims by nation."""
    o, e = _cells(spark, sf)
    return claims.arbitrate(_requests(spark, sf, o), _state(o), e)


_CELL = "((1::BIGINT << 8) + " + C.morton(["(x0 >> 20)", "(x1 >> 20)"], LV) + ")"
_BASE = f"""o AS (SELECT id, {_CELL} AS cell, x0 >> 20 AS cx, x1 >> 20 AS cy FROM ({C.ORDERS})),
n AS (SELECT DISTINCT cell, cx, cy FROM o),
e AS (SELECT a.cell, b.cell AS nbr FROM n a JOIN n b ON a.cell <> b.cell AND abs(a.cx - b.cx) <= 1 AND abs(a.cy - b.cy) <= 1),
f AS (SELECT cell, min(id) AS id FROM o GROUP BY cell),
st AS (SELECT cell, CASE id % 11 WHEN 0 THEN 'claimed' WHEN 1 THEN 'failed' WHEN 2 THEN 'enqueued' ELSE 'idle' END AS state,
  CASE WHEN id % 11 < 2 THEN (id % 5)::INT END AS owner, CASE WHEN id % 11 = 0 THEN (id % 2)::INT ELSE 0 END AS front_count FROM f)"""
Q24 = f"""WITH {_BASE},
r AS (SELECT DISTINCT s_nationkey::INT AS worker, cell FROM supplier JOIN o ON id = s_suppkey * 7),
k AS (SELECT *, {R.mix(R.mix('cell % 2147483647') + ' + worker')} AS r FROM r),
w AS (SELECT * FROM k QUALIFY row_number() OVER (PARTITION BY cell ORDER BY r, worker) = 1)
SELECT k.cell, k.worker, k.worker = w.worker AND NOT EXISTS (SELECT 1 FROM st WHERE st.cell = w.cell AND state IN ('claimed', 'failed'))
  AND NOT EXISTS (SELECT 1 FROM e JOIN st ON st.cell = e.nbr WHERE e.cell = w.cell AND state IN ('claimed', 'failed') AND owner <> w.worker)
  AND NOT EXISTS (SELECT 1 FROM e JOIN w v ON v.cell = e.nbr WHERE e.cell = w.cell AND v.worker <> w.worker AND (v.r, v.worker, v.cell) < (w.r, w.worker, w.cell)) AS granted
FROM k JOIN w USING (cell)"""


def q25_claim_release(spark, sf):
    """M7: dry cells fall idle, their owner's failed neighbours become enqueued."""
    o, e = _cells(spark, sf)
    return claims.release(_state(o), e)


Q25 = f"""WITH {_BASE}, g AS (SELECT DISTINCT e.nbr AS cell, owner FROM st JOIN e USING (cell) WHERE state = 'claimed' AND front_count = 0),
h AS (SELECT st.*, state = 'claimed' AND front_count = 0 AS let, state = 'failed' AND EXISTS (SELECT 1 FROM g WHERE g.cell = st.cell AND g.owner = st.owner) AS free FROM st)
SELECT cell, CASE WHEN let THEN 'idle' WHEN free THEN 'enqueued' ELSE state END AS state, CASE WHEN let OR free THEN NULL ELSE owner END AS owner, CASE WHEN let THEN 0 ELSE front_count END AS front_count FROM h"""


def q25b_state_audit(spark, sf):
    """M8: cells by state before and after a release; every change is one that the machine allows."""
    o, e = _cells(spark, sf)
    before = _state(o)
    both = before.select("cell", F.col("state").alias("was")).join(claims.release(before, e).select("cell", F.col("state").alias("now")), "cell")
    legal = F.array(*(F.lit(f"{a}>{b}") for (a, _), b in claims.TRANSITIONS.items()))
    return both.groupBy("was", "now").agg(F.count("*").alias("cells"), F.sum((~F.array_contains(legal, F.concat("was", F.lit(">"), "now")) & (F.col("was") != F.col("now"))).cast("long")).alias("illegal"))


Q25B = f"SELECT was, now, count(*) AS cells, 0::BIGINT AS illegal FROM (SELECT b.state AS was, a.state AS now FROM ({Q25.replace('WITH ', 'WITH ', 1)}) a JOIN (WITH {_BASE} SELECT cell, state FROM st) b USING (cell)) GROUP BY 1, 2"


def _entries(spark, sf):
    o, e = _cells(spark, sf)
    return o.select("cell", F.col("id").alias("point"), (F.col("id") % 3).cast("int").alias("stage"), (F.col("id") % 17).cast("int").alias("step"), F.col("id").alias("ord")), e


def q26_restart_fifo(spark, sf):
    """One entry a cell, in order of arrival."""
    return claims.restart_order(claims.enqueue(_entries(spark, sf)[0])).select("cell", "point", "place")


_ENT = f"""{_BASE}, q AS (SELECT cell, id AS point, id % 3 AS stage, id % 17 AS step FROM o QUALIFY row_number() OVER (PARTITION BY cell ORDER BY id % 3, id % 17, id) = 1)"""
Q26 = f"WITH {_ENT} SELECT cell, point, row_number() OVER (ORDER BY stage, step, point)::INT AS place FROM q"


def q26b_restart_shuffled(spark, sf):
    """The same set in hashed order."""
    return claims.restart_order(claims.enqueue(_entries(spark, sf)[0]), "shuffled").select("cell", "place")


Q26B = f"WITH {_ENT} SELECT cell, row_number() OVER (ORDER BY {R.mix(R.mix('cell % 2147483647') + ' + 1')}, cell)::INT AS place FROM q"


def q27_restart_greedy(spark, sf):
    """Cells taken in order, none next to another, one a worker."""
    entries, e = _entries(spark, sf)
    return claims.greedy_restart(claims.restart_order(claims.enqueue(entries)), e, 12).select("cell", "place", "worker")


Q27 = f"""WITH RECURSIVE {_ENT}, p AS (SELECT cell, row_number() OVER (ORDER BY stage, step, point) AS place FROM q),
s AS (SELECT 0::BIGINT AS place, []::BIGINT[] AS got UNION ALL
 SELECT p.place, CASE WHEN EXISTS (SELECT 1 FROM e WHERE e.cell = p.cell AND list_contains(s.got, e.nbr)) THEN got ELSE list_append(got, p.cell) END FROM s JOIN p ON p.place = s.place + 1),
z AS (SELECT got[1:12] AS got FROM s ORDER BY place DESC LIMIT 1)
SELECT cell, place::INT AS place, (row_number() OVER (ORDER BY place) - 1)::INT AS worker FROM p, z WHERE list_contains(got, cell)"""


def q42_voronoi_fill_report(spark, sf):
    """B2: the two-level fill obeys the spacing, stays inside and leaves nothing open; each point's region is its nearest generator's."""
    h = size_h(_n(spark, sf, "customer"))
    from frontfill.sources.store import stored

    # three measures read the points of one fill
    pts = stored(baselines.voronoi_kd_fill(spark, D.disc(), S.Constant(h), 6).withColumn("ord", F.col("seq")).withColumn("h_parent", F.lit(h).cast("long")))
    return _report(pts, h)


def q43_leaf_lock_counts(spark, sf):
    """Locks that inserting the customers would take with one lock a leaf."""
    c = T.customer(spark, sf)
    return baselines.leaf_lock_counts(c, tree.build_counted(c, 40, 8, names=XY), XY, 200_000)


Q43 = f"""WITH RECURSIVE {C.leaves(C.CUSTOMER, 2, 40, 8)}, {C.boxes(2, 8)},
g AS (SELECT id, greatest(0, lo0 - x0, x0 - (lo0 + side - 1)) AS g0, greatest(0, lo1 - x1, x1 - (lo1 + side - 1)) AS g1 FROM pts, boxed)
SELECT count(DISTINCT id) AS exclusive, count(*) AS shared FROM g WHERE g0 * g0 + g1 * g1 < 40000000000"""


def q47b_relaxed(spark, sf):
    """Relaxation spreads random points: no point is lost, none leaves, and the mean nearest distance grows."""
    n = _n(spark, sf, "customer") // 3
    a, b = baselines.random_points(spark, D.disc(), n), baselines.relaxed(spark, D.disc(), n, 4)
    gap = lambda p: measures.nearest(p, XY, 4_000_000).agg(F.avg(F.sqrt("d2")).alias("m")).first()["m"]
    return b.agg(F.count("*").alias("n"), F.sum((~D.disc().column(XY)).cast("long")).alias("outside")).withColumn("spread", F.lit(gap(b) > gap(a)))


Q47B = f"SELECT count(*) AS n, 0::BIGINT AS outside, true AS spread FROM ({_RND.replace('FROM customer', 'FROM customer').replace('(SELECT count(*) FROM customer)', '(SELECT count(*) // 3 FROM customer)')}) WHERE (x0 - {CENTRE}) * (x0 - {CENTRE}) + (x1 - {CENTRE}) * (x1 - {CENTRE}) <= 36000000000000"


def q58_refill(spark, sf):
    """After the spacing of one half changes, the other half's points are the same and nothing is violated."""
    h = size_h(_n(spark, sf, "customer"))
    from frontfill.sources.store import stored

    old, new = S.Constant(h), S.Step(0, CENTRE, h, h // 2)
    pts = stored(fill.fill_phased(spark, D.disc(), old, limit=32, one_task=True))
    out = stored(coordinated.refill(pts, XY, D.disc(), old, new))
    lost = pts.where(F.col("x0") < CENTRE).select(*XY).exceptAll(out.where("kept").select(*XY)).agg(F.count("*").alias("lost"))
    near = rows.within_pairs(out.where("not kept"), out, XY, h, F.lit(h // 2).cast("long")).where("a_x0 <> b_x0 or a_x1 <> b_x1").agg(F.count("*").alias("violations"))
    return lost.crossJoin(near).crossJoin(out.agg((F.sum((~F.col("kept")).cast("long")) > 2 * F.sum(F.col("kept").cast("long"))).alias("denser")))


Q58 = "SELECT 0::BIGINT AS lost, 0::BIGINT AS violations, true AS denser"


def q58b_repair(spark, sf):
    """Two fills laid over each other, repaired: what is kept has no violation, and every removed point clashed with a kept one."""
    h = size_h(_n(spark, sf, "supplier") * 4)
    from frontfill.sources.store import stored

    one = fill.fill_sequential(spark, D.disc(), S.Constant(h), fill.seeds_frame(spark, [(CENTRE, CENTRE)])).withColumn("run", F.lit(1))
    two = fill.fill_sequential(spark, D.disc(), S.Constant(h), fill.seeds_frame(spark, [(CENTRE + h // 3, CENTRE)])).withColumn("run", F.lit(2))
    both = stored(one.unionByName(two))
    kept, gone = coordinated.repair(both, XY, ["run", "seq"], h)
    kept, gone = stored(kept), stored(gone)
    v = measures.violations(kept.withColumn("ord", F.struct("run", "seq")).select("ord", "h_parent", *XY), XY, h).agg(F.count("*").alias("violations"))
    hit = rows.within_pairs(gone.select("seq", "run", "h_parent", *XY), kept.select(*XY), XY, h, F.col("a_h_parent")).select("a_run", "a_seq").distinct().agg(F.count("*").alias("c"))
    return v.crossJoin(gone.agg(F.count("*").alias("g"))).crossJoin(hit).select("violations", (F.col("g") - F.col("c")).alias("unfounded"), (F.col("g") > 0).alias("some"))


Q58B = "SELECT 0::BIGINT AS violations, 0::BIGINT AS unfounded, true AS some"

QUERIES = {n: f for n, f in list(globals().items()) if n.startswith("q") and callable(f)}
ORACLES = {
    "q08b_fill_phased_adaptive": Q08B, "q09_fill_claims_report": Q09, "q09b_gap_width": Q09B, "q09c_claims_in_tasks": Q09C, "q10_fill_coordinated_report": Q10, "q11_restart_orders": Q11, "q11b_idle_seeking": Q11B, "q24_claim_round": Q24, "q25_claim_release": Q25,
    "q25b_state_audit": Q25B, "q26_restart_fifo": Q26, "q26b_restart_shuffled": Q26B, "q27_restart_greedy": Q27, "q42_voronoi_fill_report": Q10, "q43_leaf_lock_counts": Q43, "q47b_relaxed": Q47B,
    "q58_refill": Q58, "q58b_repair": Q58B,
}

