"""Queries of the fills: sequential variants, phased, seeds."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from frontfill.catalog import clouds_sql
from frontfill.catalog import recursion as R
from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.lattice import CENTRE, RADIUS, size_h, size_h3
from frontfill.operators import measures
from frontfill.operators.tree import uniform
from frontfill.plans import fill, seams
from frontfill.sources.store import stored
from frontfill.sources import tables as T
from frontfill.sources.tables import table

DISC = f"({{x}}0 - {CENTRE}) * ({{x}}0 - {CENTRE}) + ({{x}}1 - {CENTRE}) * ({{x}}1 - {CENTRE}) <= {RADIUS * RADIUS}"
C = (CENTRE, CENTRE)


def _count(spark, sf, name):
    return table(spark, sf, name).count()


def _first_row(spark, sf, d=2):
    """The seed: of the suppliers inside, the row nearest to the centre."""
    names = [f"x{a}" for a in range(d)]
    rows = T.supplier(spark, sf, d).where(D.disc(d=d).column(names))
    gap = sum(((F.col(n) - CENTRE) * (F.col(n) - CENTRE) for n in names[1:]), (F.col("x0") - CENTRE) * (F.col("x0") - CENTRE))
    return rows.orderBy(gap, "id", *names).limit(1).select(F.lit(0).cast("long").alias("ord"), *names)


def _from_first_row(size, name, inside, d=2):
    """Parameters and seeds of the same in SQL."""
    gap = " + ".join(f"(x{a} - {CENTRE}) * (x{a} - {CENTRE})" for a in range(d))
    order = ", ".join([gap, "id", *(f"x{a}" for a in range(d))])
    lists = ", ".join(f"coalesce(list(x{a} ORDER BY {order})[1:1], []::BIGINT[]) AS b{a}" for a in range(d))
    seeds = f"SELECT {lists} FROM ({clouds_sql.SUPPLIER}) WHERE {inside.format(x='x')}"
    return f"SELECT * FROM (SELECT {size.format(n='count(*)')} AS {name} FROM supplier), ({seeds})", [f"b{a}" for a in range(d)]


def _cols(df, d):
    return df.select("seq", *(f"x{a}" for a in range(d)), "h_parent", "parent")


def q01_fill_disc_seq(spark, sf):
    """M1: disc, one seed, constant spacing sized from the supplier rows; the seed is the supplier nearest to the centre."""
    h = size_h(_count(spark, sf, "supplier"))
    return _cols(fill.fill_sequential(spark, D.disc(), S.Constant(h), _first_row(spark, sf)), 2)


Q01 = R.sequential(*_from_first_row(R.H2, "h", DISC), DISC, "h", 2)


def q02_fill_segment_seq(spark, sf):
    """M1 in one dimension: a segment from its left end, sized from the benchmark rows."""
    n = _count(spark, sf, "benchmark")
    h = 16_000_000 // n
    dom = D.Box((100_000,), (16_100_000,))
    return _cols(fill.fill_sequential(spark, dom, S.Constant(h), fill.seeds_frame(spark, [(100_000,)], 1), d=1), 1)


Q02 = R.sequential("SELECT 16000000 // count(*) AS h FROM benchmark", ["[100000]::BIGINT[]"], "{x}0 >= 100000 AND {x}0 <= 16100000", "h", 1)

BALL3 = " + ".join(f"({{x}}{a} - {CENTRE}) * ({{x}}{a} - {CENTRE})" for a in range(3)) + f" <= {RADIUS * RADIUS}"


def q03_fill_ball_seq(spark, sf):
    """M1 in three dimensions: a ball from the supplier nearest to its centre."""
    h = size_h3(_count(spark, sf, "supplier"))
    return _cols(fill.fill_sequential(spark, D.disc(d=3), S.Constant(h), _first_row(spark, sf, 3), d=3), 3)


Q03 = R.sequential(*_from_first_row(R.H3, "h", BALL3, 3), BALL3, "h", 3)


def q04_fill_variable_seq(spark, sf):
    """Spacing grows linearly along the first axis; a candidate is tested with its parent's spacing."""
    h = size_h(_count(spark, sf, "supplier"))
    return _cols(fill.fill_sequential(spark, D.disc(), S.Linear(h // 2, 3 * h // 2), _first_row(spark, sf)), 2)


Q04 = R.sequential(*_from_first_row(R.H2, "hh", DISC), DISC, "(hh // 2 + (({x}0 * (3 * hh // 2 - hh // 2)) >> 24))", 2)


def q05_fill_annulus_boundary_seeds(spark, sf):
    """M1e, M19: a ring filled from eight seeds on its inner border."""
    h = size_h(40 * _count(spark, sf, "region"))
    r = RADIUS // 2
    a = 2121320
    seeds = [(CENTRE + x, CENTRE + y) for x, y in ((r + 2, 0), (a + 2, a + 2), (0, r + 2), (-a - 2, a + 2), (-r - 2, 0), (-a - 2, -a - 2), (0, -r - 2), (a + 2, -a - 2))]
    return _cols(fill.fill_sequential(spark, D.annulus(C, r, RADIUS), S.Constant(h), fill.seeds_frame(spark, seeds)), 2)


_R = RADIUS // 2 + 2
_A = 2121322
Q05 = R.sequential(
    f"SELECT {R.H2.format(n='(40 * count(*))')} AS h FROM region",
    ["[" + ", ".join(str(CENTRE + v) for v in axis) + "]::BIGINT[]" for axis in ((_R, _A, 0, -_A, -_R, -_A, 0, _A), (0, _A, _R, _A, 0, -_A, -_R, -_A))],
    DISC + f" AND ({{x}}0 - {CENTRE}) * ({{x}}0 - {CENTRE}) + ({{x}}1 - {CENTRE}) * ({{x}}1 - {CENTRE}) > {(RADIUS // 2) ** 2}",
    "h",
    2,
)


def q06_fill_annulus_candidates(spark, sf):
    """M1d: candidates at one to two spacings from their parent."""
    h = size_h(_count(spark, sf, "supplier"))
    return _cols(fill.fill_sequential(spark, D.disc(), S.Constant(h), _first_row(spark, sf), annulus=True), 2)


Q06 = R.sequential(*_from_first_row(R.H2, "h", DISC), DISC, "h", 2, annulus=True)

LEVEL7 = 3
#: the customers whose place lies in the disc
INSIDE = f"(SELECT greatest(1, count(*)) FROM ({clouds_sql.CUSTOMER}) WHERE {DISC.format(x='x')})"


def _inside(spark, sf):
    return max(1, T.customer(spark, sf).where(D.disc().column(["x0", "x1"])).count())



def q07_fill_phased(spark, sf):
    """The phase-coloured fill, point for point and in its canonical order; spacing sized from the customers inside."""
    h = size_h(_inside(spark, sf))
    return fill.fill_phased(spark, D.disc(), S.Constant(h), limit=32, one_task=True).select("x0", "x1", "h", "h_parent", "cell", "by_cell", "stage", "phase", "seq")


Q07 = R.phased(f"SELECT {R.H2.format(n=INSIDE)} AS h", LEVEL7, DISC, LEVEL7)


def q07b_fill_phased_distributed(spark, sf):
    """M11 again with the distributed form forced: the same rows from several tasks and jobs."""
    h = size_h(_inside(spark, sf))
    return fill.fill_phased(spark, D.disc(), S.Constant(h), limit=32, cells_per_task=3).select("x0", "x1", "h", "h_parent", "cell", "by_cell", "stage", "phase", "seq")


def fill_seams_points(spark, sf):
    """All blocks at once, then the seams between them; the points in their canonical order."""
    h = size_h(_count(spark, sf, "customer"))
    return seams.fill_seams(spark, D.disc(), S.Constant(h), block_points=300)


def q07d_seams_report(spark, sf):
    """M10, M11 by blocks and seams, audited: no violation, nothing outside, nothing open, as dense as it must be, most of it in the first family."""
    h = size_h(max(1500, _inside(spark, sf)))
    pts = stored(seams.fill_seams(spark, D.disc(), S.Constant(h), block_points=300).withColumn("ord", F.struct("stage", "phase", "by_zone", "seq")))
    xy = ["x0", "x1"]
    bad = measures.violations(pts.select("ord", "h_parent", *xy), xy, h).agg(F.count("*").alias("violations"))
    out = pts.agg(F.sum((~D.disc().column(xy)).cast("long")).alias("outside"), (F.count("*") * h * h / (3.14159265 * RADIUS * RADIUS)).alias("density"), F.avg((F.col("phase") == 0).cast("double")).alias("first"))
    free = measures.open_candidates(pts.select(*xy, "h"), D.disc(), 2, h).agg(F.count("*").alias("open"))
    return bad.crossJoin(out).crossJoin(free).select("violations", "outside", "open", (F.col("density").between(0.8, 1.1)).alias("dense"), (F.col("first") > 0.5).alias("mostly_first"))


Q07D = "SELECT 0::BIGINT AS violations, 0::BIGINT AS outside, 0::BIGINT AS open, true AS dense, true AS mostly_first"


def q01b_queue_orders(spark, sf):
    """M1g: last-in-first-out and random fronts leave no violation and nothing open, in other points than the first-in-first-out one."""
    h = size_h(_count(spark, sf, "supplier"))
    out = None
    xy = ["x0", "x1"]
    for order in ("fifo", "lifo", "random"):
        pts = stored(_cols(fill.fill_sequential(spark, D.disc(), S.Constant(h), _first_row(spark, sf), order=order), 2).withColumn("h", F.lit(h).cast("long")))
        bad = measures.violations(pts.select(F.col("seq").alias("ord"), "h_parent", *xy), xy, h).agg(F.count("*").alias("violations"))
        free = measures.open_candidates(pts.select(*xy, "h"), D.disc(), 2, h).agg(F.count("*").alias("open"))
        row = bad.crossJoin(free).crossJoin(pts.agg((F.count("*") > 0.7 * _count(spark, sf, "supplier")).alias("filled"))).withColumn("queue", F.lit(order))
        out = row if out is None else out.unionByName(row)
    return out


Q01B = "SELECT 0::BIGINT AS violations, 0::BIGINT AS open, true AS filled, queue FROM (VALUES ('fifo'), ('lifo'), ('random')) t(queue)"
BOX = ((1_000_000, 2_000_000), (13_000_000, 9_000_000))
KITE = ((2_000_000, 2_000_000), (15_000_000, 4_000_000), (9_000_000, 14_000_000))
BOX_AREA = (BOX[1][0] - BOX[0][0]) * (BOX[1][1] - BOX[0][1])
KITE_AREA = abs(sum(a[0] * b[1] - b[0] * a[1] for a, b in zip(KITE, (*KITE[1:], KITE[0]), strict=True))) // 2


def _h_inside(spark, sf, domain, area):
    """Spacing at which a region holds about as many points as suppliers lie in it."""
    n = max(1, T.supplier(spark, sf).where(domain.column(["x0", "x1"])).count())
    return math.floor(math.sqrt(0.8 * area / n))


def q05b_fill_box_boundary_seeds(spark, sf):
    """M1e: a box filled from seeds on its faces, spacing sized from the suppliers inside."""
    dom = D.Box(*BOX)
    h = _h_inside(spark, sf, dom, BOX_AREA)
    return _cols(fill.fill_sequential(spark, dom, S.Constant(h), fill.seeds_frame(spark, fill.seeds_box(*BOX, h))), 2)


def q05c_fill_polygon_boundary_seeds(spark, sf):
    """M1e: a polygon filled from seeds on its edges, spacing sized from the suppliers inside."""
    dom = D.Polygon(KITE)
    h = _h_inside(spark, sf, dom, KITE_AREA)
    return _cols(fill.fill_sequential(spark, dom, S.Constant(h), fill.seeds_frame(spark, fill.seeds_polygon(KITE, h))), 2)


def _on_border(inside, area, places):
    """Parameters and seeds in SQL: ``places`` (``e, i, j, x0, x1`` over ``g``, which has ``h``), inside and thinned in order."""
    return f"""WITH RECURSIVE g AS (SELECT CAST(FLOOR(SQRT(0.8::DOUBLE * {area} / greatest(1, count(*)))) AS BIGINT) AS h FROM ({clouds_sql.SUPPLIER}) WHERE {inside.format(x='x')}),
pl AS ({places}),
o AS (SELECT row_number() OVER (ORDER BY e, i, j) AS r, x0 AS n0, x1 AS n1 FROM pl WHERE {inside.format(x='x')}),
th AS (SELECT 0::BIGINT AS r, []::BIGINT[] AS b0, []::BIGINT[] AS b1 UNION ALL
 SELECT r + 1, CASE WHEN ok THEN list_append(b0, n0) ELSE b0 END, CASE WHEN ok THEN list_append(b1, n1) ELSE b1 END
 FROM (SELECT th.r, b0, b1, n0, n1, len(list_filter(range(1, len(b0) + 1), lambda i: (b0[i] - n0) * (b0[i] - n0) + (b1[i] - n1) * (b1[i] - n1) < h * h)) = 0 AS ok FROM th JOIN o ON o.r = th.r + 1, g))
SELECT h, b0, b1 FROM g, (SELECT b0, b1 FROM th ORDER BY r DESC LIMIT 1)""", ["b0", "b1"]


IN_BOX = " AND ".join(f"{{x}}{a} >= {BOX[0][a]} AND {{x}}{a} <= {BOX[1][a]}" for a in range(2))
_W = [BOX[1][a] - BOX[0][a] for a in range(2)]
_N = [f"greatest(1, {w} // h)" for w in _W]
_FACES = f"""SELECT 0 AS e, i, j, {BOX[0][0]} + {_W[0]}::BIGINT * i // {_N[0]} AS x0, {BOX[0][1]} + {_W[1]}::BIGINT * j // {_N[1]} AS x1
FROM (SELECT h, i, unnest(range(0, {_N[1]} + 1)) AS j FROM (SELECT h, unnest(range(0, {_N[0]} + 1)) AS i FROM g)) WHERE i IN (0, {_N[0]}) OR j IN (0, {_N[1]})"""
Q05B = R.sequential(*_on_border(IN_BOX, BOX_AREA, _FACES), IN_BOX, "h", 2)
_ODD = " + ".join(
    f"(({{x}}1 >= {min(a, b, key=lambda c: c[1])[1]} AND {{x}}1 < {max(a, b, key=lambda c: c[1])[1]} AND ({{x}}0 - {min(a, b, key=lambda c: c[1])[0]}) * {abs(b[1] - a[1])} < ({{x}}1 - {min(a, b, key=lambda c: c[1])[1]}) * ({max(a, b, key=lambda c: c[1])[0] - min(a, b, key=lambda c: c[1])[0]}))::INT)"
    for a, b in zip(KITE, (*KITE[1:], KITE[0]), strict=True)
)
IN_KITE = f"({_ODD}) % 2 = 1"


def _edge(e, a, b):
    n = f"greatest(1, {math.isqrt((b[0] - a[0]) ** 2 + (b[1] - a[1]) ** 2)} // h)"
    # a step back is rounded down as well
    part = lambda v: f"{v}::BIGINT * i // {n}" if v >= 0 else f"-(({-v}::BIGINT * i + {n} - 1) // {n})"
    return f"SELECT {e} AS e, i, 0 AS j, {a[0]} + {part(b[0] - a[0])} AS x0, {a[1]} + {part(b[1] - a[1])} AS x1 FROM (SELECT h, unnest(range(0, {n})) AS i FROM g)"


Q05C = R.sequential(*_on_border(IN_KITE, KITE_AREA, " UNION ALL ".join(_edge(e, a, b) for e, (a, b) in enumerate(zip(KITE, (*KITE[1:], KITE[0]), strict=True)))), IN_KITE, "h", 2)


def q29_seeds_per_cell(spark, sf):
    """Centres of the work cells that lie in the region."""
    h = size_h(_count(spark, sf, "customer"))
    return fill.seeds_per_cell(uniform(spark, 4, 2), D.disc()).select("cell", "x0", "x1", F.lit(h).alias("h"))


_MOR4 = " + ".join(f"((((x) >> {b}) & 1) << {2 * b + 1}) + ((((y) >> {b}) & 1) << {2 * b})" for b in range(4))
Q29 = f"""
WITH g AS (SELECT a.x, b.y FROM range(16) a(x), range(16) b(y)),
m AS (SELECT 256 + {_MOR4} AS cell, x * 1048576 + 524288 AS x0, y * 1048576 + 524288 AS x1 FROM g)
SELECT cell, x0, x1, (SELECT {R.H2.format(n='count(*)')} FROM customer) AS h FROM m WHERE {DISC.format(x='x')}
"""


def q28_seeds_coarse(spark, sf):
    """Seeds from a fill with four times the spacing."""
    h = size_h(_count(spark, sf, "orders"))
    return fill.seeds_coarse(spark, D.disc(), S.Constant(h), fill.seeds_frame(spark, [C]), 4 * 4)


Q28 = R.sequential(f"SELECT 16 * {R.H2.format(n='count(*)')} AS h FROM orders", [f"[{CENTRE}]::BIGINT[]"] * 2, DISC, "h", 2)
Q28 = f"SELECT seq AS ord, x0, x1 FROM ({Q28})"


def q30_seeds_relaxed(spark, sf):
    """One relaxed seed a nation; exact number, inside, spread: a report of what must hold."""
    n = _count(spark, sf, "nation")
    x = fill.seeds_relaxed(D.disc(), n)
    rows = fill.seeds_frame(spark, x)
    a, b = rows.alias("a"), rows.alias("b")
    gap = a.crossJoin(b).where("a.ord < b.ord").select(F.expr("(a.x0-b.x0)*(a.x0-b.x0)+(a.x1-b.x1)*(a.x1-b.x1)").alias("g")).agg(F.min("g").alias("g"))
    spread = int(RADIUS * RADIUS / (2 * n))
    return rows.agg(F.count("*").alias("n"), F.sum((~D.disc().column(["x0", "x1"])).cast("long")).alias("outside")).crossJoin(gap).select("n", "outside", (F.col("g") > spread).alias("spread"))


Q30 = "SELECT count(*) AS n, 0::BIGINT AS outside, true AS spread FROM nation"

QUERIES = {f.__name__: f for f in (q01_fill_disc_seq, q02_fill_segment_seq, q03_fill_ball_seq, q04_fill_variable_seq, q05_fill_annulus_boundary_seeds, q06_fill_annulus_candidates, q07_fill_phased, q07b_fill_phased_distributed, q07d_seams_report, q01b_queue_orders, q05b_fill_box_boundary_seeds, q05c_fill_polygon_boundary_seeds, q28_seeds_coarse, q29_seeds_per_cell, q30_seeds_relaxed)}
ORACLES = {
    "q01_fill_disc_seq": Q01, "q02_fill_segment_seq": Q02, "q03_fill_ball_seq": Q03, "q04_fill_variable_seq": Q04, "q05_fill_annulus_boundary_seeds": Q05,
    "q06_fill_annulus_candidates": Q06, "q07_fill_phased": Q07, "q07b_fill_phased_distributed": Q07, "q07d_seams_report": Q07D, "q01b_queue_orders": Q01B, "q05b_fill_box_boundary_seeds": Q05B, "q05c_fill_polygon_boundary_seeds": Q05C, "q28_seeds_coarse": Q28, "q29_seeds_per_cell": Q29, "q30_seeds_relaxed": Q30,
}
