"""Queries of the work tree: building, neighbours, levels, colours, balance."""

from __future__ import annotations

from pyspark.sql import functions as F

from frontfill.catalog import clouds_sql as C
from frontfill.catalog import recursion as R
from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.lattice import size_h
from frontfill.operators import measures, rows, tree
from frontfill.sources import tables as T

BITS = {1: 12, 2: 12, 3: 8}


def _built(cloud, d, limit, deep):
    return tree.build_counted(cloud, limit, deep, names=[f"x{a}" for a in range(d)])


def q12_work_tree_2d(spark, sf):
    """M3 with exact counts: orders, limit 100."""
    return _built(T.orders(spark, sf), 2, 100, BITS[2])


def q13_work_tree_3d(spark, sf):
    """M3 with exact counts: lineitem, limit 500."""
    return _built(T.lineitem(spark, sf), 3, 500, BITS[3])


def q14_work_tree_1d(spark, sf):
    """M3 with exact counts: benchmark lengths, limit 4."""
    return _built(T.benchmark(spark, sf), 1, 4, BITS[1])


def q15_work_tree_ties(spark, sf):
    """Many coincident points: cells that cannot fall under the limit stop at the deepest level."""
    return _built(T.part(spark, sf), 2, 8, 6)


def _tree_sql(cloud, d, limit, deep):
    return f"WITH {C.leaves(cloud, d, limit, deep)} SELECT cell, level, est FROM leaves"


def q16_uniform_tree(spark, sf):
    """The full tree whose cells fall under the limit for a spacing sized from customer."""
    h = size_h(T.table(spark, sf, "customer").count())
    return tree.with_boxes(tree.uniform(spark, tree.uniform_level(100, h, 2), 2), 2).select("cell", "level", "lo0", "lo1", "side")


Q16 = f"""
WITH h AS (SELECT {R.H2.format(n='count(*)')} AS h FROM customer),
l AS (SELECT min(v) AS v FROM range(0, 20) t(v), h WHERE 0.89 * pow((16777216 >> v::INT)::DOUBLE / h, 2) <= 100 OR (16777216 >> (v + 1)::INT) < 3 * h + 6),
g AS (SELECT a.x, b.y, v FROM l, range(0, 64) a(x), range(0, 64) b(y) WHERE x < (1 << v::INT) AND y < (1 << v::INT))
SELECT (1::BIGINT << (2 * v)::INT) + {C.morton(['x', 'y'], 6)} AS cell, v::INT AS level, x * (16777216 >> v::INT) AS lo0, y * (16777216 >> v::INT) AS lo1,
       (16777216 >> v::INT)::BIGINT AS side FROM g
"""


def q17_estimates(spark, sf):
    """M2: expected points a cell for a linear spacing, over midpoints, clipped to the disc."""
    h = size_h(T.table(spark, sf, "customer").count())
    est = tree.estimate(tree.uniform(spark, 3, 2), S.Linear(h // 2, 2 * h), 2, D.disc())
    return est.select("cell", F.round("est", 4).alias("est"))


_XM = "(c * 2097152 + (2097152 * (2 * q + 1)) // 8)"
Q17 = f"""
WITH h AS (SELECT {R.H2.format(n='count(*)')} AS h FROM customer),
g AS (SELECT a.c AS cx, b.c AS cy, p.q AS qx, r.q AS qy FROM range(0, 8) a(c), range(0, 8) b(c), range(0, 4) p(q), range(0, 4) r(q)),
m AS (SELECT 64 + {C.morton(['cx', 'cy'], 3)} AS cell, {_XM.replace('c *', 'cx *').replace('q +', 'qx +')} AS x, {_XM.replace('c *', 'cy *').replace('q +', 'qy +')} AS y FROM g)
SELECT cell, round(0.89::DOUBLE * sum(CASE WHEN (x - 8388608) * (x - 8388608) + (y - 8388608) * (y - 8388608) <= 36000000000000
  THEN pow(2097152 / 4.0::DOUBLE / (h // 2 + ((x * (2 * h - h // 2)) >> 24)), 2.0) ELSE 0 END), 4) AS est FROM m, h GROUP BY cell
"""


def q18_neighbors_uniform(spark, sf):
    """M5 on the full tree of level 3 over the occupied cells of orders."""
    cells = T.orders(spark, sf).select(tree.point_key(["x0", "x1"], 3).alias("cell")).distinct().withColumn("level", F.lit(3))
    return tree.neighbours(cells, 2)


def _touch(d):
    return " AND ".join(f"a.lo{i} <= b.lo{i} + b.side AND b.lo{i} <= a.lo{i} + a.side" for i in range(d))


_OCC = f"SELECT DISTINCT 64 + {C.morton(['(x0 >> 21)', '(x1 >> 21)'], 3)} AS cell, 3 AS level FROM ({C.ORDERS})"
Q18 = f"WITH leaves AS ({_OCC}), {C.boxes(2, 3)} SELECT a.cell, b.cell AS nbr FROM boxed a JOIN boxed b ON a.cell <> b.cell AND {_touch(2)}"


def q19_neighbors_mixed(spark, sf):
    """M5 on the adaptive tree of events: neighbours at any level."""
    return tree.neighbours(_built(T.events(spark, sf), 2, 200, 10), 2)


def _mixed(cloud, d, limit, deep, select):
    return f"WITH {C.leaves(cloud, d, limit, deep)}, {C.boxes(d, deep)} {select}"


Q19 = _mixed(C.EVENTS, 2, 200, 10, f"SELECT a.cell, b.cell AS nbr FROM boxed a JOIN boxed b ON a.cell <> b.cell AND {_touch(2)}")


def q20_spatial_levels(spark, sf):
    """M4: level of the point tree around each work cell."""
    return tree.spatial_levels(_built(T.events(spark, sf), 2, 200, 10), 2).select("cell", "level", "spatial_level")


Q20 = _mixed(C.EVENTS, 2, 200, 10, f"SELECT a.cell, any_value(a.level) AS level, (max(b.level) + 1)::INT AS spatial_level FROM boxed a JOIN boxed b ON {_touch(2)} GROUP BY a.cell")


def q21_point_tree_40(spark, sf):
    """Leaves of at most 40 points where levels allow."""
    return _built(T.lineitem(spark, sf), 3, 40, BITS[3])


def q21b_points_in_cell(spark, sf):
    """The orders of one cell of the full tree, found by ranges of their coordinates."""
    mid = (1 << 8) + 0b11000000
    return tree.points_in_cell(T.orders(spark, sf), mid, 4).select("id", "x0", "x1")


Q21B = f"SELECT id, x0, x1 FROM ({C.ORDERS}) WHERE x0 >> 20 = 8 AND x1 >> 20 = 8"


def q22_balance(spark, sf):
    """After balancing no two neighbours differ by more than a level and the cells still tile the root cube."""
    cells = tree.balance(_built(T.events(spark, sf), 2, 200, 10), 2)
    e = tree.neighbours(cells, 2).join(cells.select("cell", F.col("level").alias("l0")), "cell").join(cells.select(F.col("cell").alias("nbr"), F.col("level").alias("l1")), "nbr")
    jumps = e.agg(F.sum((F.abs(F.col("l0") - F.col("l1")) > 1).cast("long")).alias("jumps"))
    area = tree.with_boxes(cells, 2).agg(F.sum(F.col("side") * F.col("side")).alias("area"))
    return jumps.crossJoin(area)


Q22 = "SELECT 0::BIGINT AS jumps, 281474976710656::BIGINT AS area"


def q23_colours(spark, sf):
    """Colours of the occupied full-tree cells, and links between equal colours (none)."""
    cells = T.events(spark, sf).select(tree.point_key(["x0", "x1"], 5).alias("cell")).distinct().withColumn("level", F.lit(5))
    tinted = tree.colours(cells, 2, by_level=False).select("cell", "colour")
    e = tree.neighbours(cells, 2).join(tinted, "cell").join(tinted.select(F.col("cell").alias("nbr"), F.col("colour").alias("other")), "nbr")
    clash = e.groupBy("cell").agg(F.sum((F.col("colour") == F.col("other")).cast("long")).alias("clashes"))
    return tinted.join(clash, "cell", "left").select("cell", "colour", F.coalesce("clashes", F.lit(0)).cast("long").alias("clashes"))


Q23 = f"WITH c AS (SELECT DISTINCT x0 >> 19 AS x, x1 >> 19 AS y FROM ({C.EVENTS})) SELECT 1024 + {C.morton(['x', 'y'], 5)} AS cell, (2 * (x & 1) + (y & 1))::INT AS colour, 0::BIGINT AS clashes FROM c"


def q08_tree_width(spark, sf):
    """M3d: leaves of the orders tree too narrow for a spacing."""
    return tree.check_width(_built(T.orders(spark, sf), 2, 100, BITS[2]), S.Constant(400_000), 2)


Q08 = _mixed(C.ORDERS, 2, 100, BITS[2], "SELECT cell, side, 1200006::BIGINT AS need FROM boxed WHERE side < 1200006")


def q48_occupancy(spark, sf):
    """Points a leaf against the limit."""
    cloud = T.lineitem(spark, sf)
    cells = _built(cloud, 3, 500, BITS[3])
    return measures.occupancy(rows.locate(cloud, cells, ["x0", "x1", "x2"]), cells, 500, 3)


Q48 = f"WITH {C.leaves(C.LINEITEM, 3, 500, BITS[3])} SELECT count(*) AS cells, min(est) AS fewest, sum(est)::BIGINT AS points, max(est) AS most, sum((est > 500)::INT)::BIGINT AS over, sum((est * 8 < 500)::INT)::BIGINT AS under FROM leaves"


def q49_tree_stats(spark, sf):
    """Cells and links by level."""
    cells = _built(T.orders(spark, sf), 2, 100, BITS[2])
    return measures.tree_stats(cells, tree.neighbours(cells, 2))


Q49 = _mixed(C.ORDERS, 2, 100, BITS[2], f", d AS (SELECT a.cell, count(*) AS n FROM boxed a JOIN boxed b ON a.cell <> b.cell AND {_touch(2)} GROUP BY 1) SELECT level, count(*) AS cells, sum(coalesce(n, 0))::BIGINT AS links, max(coalesce(n, 0))::BIGINT AS most_links FROM boxed LEFT JOIN d USING (cell) GROUP BY level")


def q49b_claim_degree(spark, sf):
    """Neighbours that a claim examines."""
    return measures.claim_degree(tree.neighbours(_built(T.orders(spark, sf), 2, 100, BITS[2]), 2))


Q49B = _mixed(C.ORDERS, 2, 100, BITS[2], f", d AS (SELECT a.cell, count(*) AS degree FROM boxed a JOIN boxed b ON a.cell <> b.cell AND {_touch(2)} GROUP BY 1) SELECT degree, count(*) AS cells FROM d GROUP BY 1")


def q50_completeness(spark, sf):
    """How full each node of the tree is, with half of the orders present."""
    cloud = T.orders(spark, sf)
    cells = _built(cloud, 2, 100, BITS[2])
    return measures.completeness(rows.locate(cloud.where("x0 < 8388608"), cells, ["x0", "x1"]), cells, 2)


Q50 = f"""WITH {C.leaves(C.ORDERS, 2, 100, BITS[2])},
l AS (SELECT level AS lv, cell AS leaf, est FROM leaves),
p AS (SELECT leaf, count(*) AS n FROM pts JOIN l ON leaf = (1::BIGINT << (2 * lv)) + {C.morton(['(x0 >> (24 - lv))', '(x1 >> (24 - lv))'], BITS[2])} WHERE x0 < 8388608 GROUP BY leaf)
SELECT leaf >> (2 * k)::INT AS node, (lv - k)::INT AS level, sum(coalesce(n, 0))::BIGINT AS n, sum(est)::BIGINT AS est
FROM l LEFT JOIN p USING (leaf), range(0, 13) t(k) WHERE k <= lv GROUP BY 1, 2"""


def q50b_limit_quantisation(spark, sf):
    """Limits that build the same tree."""
    cloud = T.customer(spark, sf)
    return measures.distinct_trees([(n, _built(cloud, 2, n, 8)) for n in (32, 50, 100, 200, 500, 1000)])


Q50B = "WITH " + ", ".join(
    C.leaves(C.CUSTOMER, 2, n, 8).replace("pts ", f"pts{n} ").replace("FROM pts", f"FROM pts{n}").replace("nodes", f"nodes{n}").replace("deepest", f"deepest{n}").replace("every", f"every{n}").replace("leaves", f"leaves{n}").replace(f"pts{n}{n}", f"pts{n}") for n in (32, 50, 100, 200, 500, 1000)
) + ", t AS (" + " UNION ALL ".join(f'SELECT {n}::BIGINT AS "limit", count(*) AS cells, sum((cell * 48271 + 11) % 2147483647)::BIGINT AS print FROM leaves{n}' for n in (32, 50, 100, 200, 500, 1000)) + ') SELECT *, min("limit") OVER (PARTITION BY cells, print) AS same_as FROM t'


def q50c_merged_tree(spark, sf):
    """Leaves of the point tree with the work cell above each."""
    cloud = T.orders(spark, sf)
    return tree.merged_tree(_built(cloud, 2, 640, 12), cloud, 2, 40).select("cell", "level", "est", "work_cell")


Q50C = f"""WITH {C.leaves(C.ORDERS, 2, 40, 24)},
{C.leaves(C.ORDERS, 2, 640, 12).replace('pts ', 'wpts ').replace('FROM pts', 'FROM wpts').replace('nodes', 'wnodes').replace('deepest', 'wdeepest').replace('every', 'wevery').replace('leaves', 'wleaves')}
SELECT f.cell, f.level, f.est, w.cell AS work_cell FROM leaves f LEFT JOIN wleaves w ON w.level <= f.level AND w.cell = f.cell >> (2 * (f.level - w.level))"""

QUERIES = {n: f for n, f in list(globals().items()) if n.startswith("q") and callable(f)}
ORACLES = {
    "q08_tree_width": Q08,
    "q12_work_tree_2d": _tree_sql(C.ORDERS, 2, 100, BITS[2]),
    "q13_work_tree_3d": _tree_sql(C.LINEITEM, 3, 500, BITS[3]),
    "q14_work_tree_1d": _tree_sql(C.BENCHMARK, 1, 4, BITS[1]),
    "q15_work_tree_ties": _tree_sql(C.PART, 2, 8, 6),
    "q16_uniform_tree": Q16, "q17_estimates": Q17, "q18_neighbors_uniform": Q18, "q19_neighbors_mixed": Q19, "q20_spatial_levels": Q20,
    "q21_point_tree_40": _tree_sql(C.LINEITEM, 3, 40, BITS[3]),
    "q21b_points_in_cell": Q21B, "q22_balance": Q22, "q23_colours": Q23, "q48_occupancy": Q48, "q49_tree_stats": Q49, "q49b_claim_degree": Q49B, "q50_completeness": Q50,
    "q50b_limit_quantisation": Q50B, "q50c_merged_tree": Q50C,
}
