"""Queries on row clouds: thinning, spatial audits, halos, nearest generators, plain baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from frontfill.catalog import clouds_sql as C
from frontfill.catalog import recursion as R
from frontfill.catalog.trees import BITS, _built
from frontfill.functions import domain as D
from frontfill.functions.directions import candidates, directions
from frontfill.functions.lattice import CENTRE, RADIUS, mix, size_h
from frontfill.operators import measures, rows, tree
from frontfill.plans import baselines
from frontfill.sources import tables as T

XY = ["x0", "x1"]
H31, H32, H34 = 700_000, 400_000, 900_000


def q31_thin_customer(spark, sf):
    """A spacing-constrained subset of the customers."""
    return rows.thin(T.customer(spark, sf), XY, H31)


def q32_thin_part(spark, sf):
    """M20 on a coarse grid with many coincident rows."""
    return rows.thin(T.part(spark, sf), XY, H32)


_H33 = {"click": 300_000, "purchase": 900_000, "signup": 600_000}


def _h33():
    e = F.lit(450_000)
    for k, v in _H33.items():
        e = F.when(F.col("grp") == k, F.lit(v)).otherwise(e)
    return e.cast("long")


def q33_thin_events(spark, sf):
    """M20 with a spacing by event type, all events."""
    return rows.thin(T.events(spark, sf), XY, _h33(), h_most=900_000)


Q33H = "CASE " + " ".join(f"WHEN grp = '{k}' THEN {v}" for k, v in _H33.items()) + " ELSE 450000 END::BIGINT"


def q34_thin_embeddings(spark, sf):
    """M20 on the first two components."""
    return rows.thin(T.embeddings(spark, sf, 2), XY, H34)


def q34b_thin_embeddings_3d(spark, sf):
    """M20 on the first three components."""
    return rows.thin(T.embeddings(spark, sf, 3), ["x0", "x1", "x2"], 1_500_000)


def q35_thin_by_group(spark, sf):
    """M20 for each nation apart."""
    return rows.thin(T.customer(spark, sf), XY, 2_000_000, group="grp")


def q35b_thin_documents_by_lang(spark, sf):
    """M20 for each language apart."""
    return rows.thin(T.documents(spark, sf), XY, 30_000, group="grp")


def q35c_thin_labelled(spark, sf):
    """M20 by label quality: only labelled documents, one stratum a quality."""
    labels = T.table(spark, sf, "labels").select(F.col("doc_id").alias("id"), F.col("quality").cast("string").alias("q"))
    return rows.thin(T.documents(spark, sf).join(labels, "id").select("id", "x0", "x1", "q"), XY, 60_000, group="q")


def q36_violations(spark, sf):
    """A2 on rows: pairs of customers nearer than a radius."""
    c = T.customer(spark, sf).withColumn("ord", F.col("id")).withColumn("h_parent", F.lit(150_000).cast("long"))
    return measures.violations(c.select("ord", "h_parent", *XY), XY, 150_000).select("a_ord", "b_ord", "d2")


Q36 = f"WITH c AS ({C.CUSTOMER}) SELECT a.id AS a_ord, b.id AS b_ord, d2 FROM (SELECT a, b, (a.x0-b.x0)*(a.x0-b.x0)+(a.x1-b.x1)*(a.x1-b.x1) AS d2 FROM c a JOIN c b ON b.id < a.id) WHERE d2 < 22500000000"


def q37_nn_regularity(spark, sf):
    """A6 on rows: nearest-neighbour distances over a spacing."""
    r = measures.regularity(T.customer(spark, sf), XY, 300_000)
    return r.select("n", F.round("mean", 6).alias("mean"), F.round("spread", 6).alias("spread"), *(F.round(F.col("quartiles")[i], 6).alias(f"q{i}") for i in range(5)))


Q37 = f"""WITH c AS ({C.CUSTOMER}), d AS (SELECT a.id, min((a.x0-b.x0)*(a.x0-b.x0)+(a.x1-b.x1)*(a.x1-b.x1)) AS d2 FROM c a JOIN c b ON a.id <> b.id GROUP BY a.id),
r AS (SELECT sqrt(d2::DOUBLE) / 300000.0::DOUBLE AS r FROM d WHERE d2 < 360000000000)
SELECT count(*) AS n, round(avg(r), 6) AS mean, round(stddev_pop(r), 6) AS spread, round(quantile_cont(r, 0.0), 6) AS q0, round(quantile_cont(r, 0.25), 6) AS q1,
 round(quantile_cont(r, 0.5), 6) AS q2, round(quantile_cont(r, 0.75), 6) AS q3, round(quantile_cont(r, 1.0), 6) AS q4 FROM r"""


def q38_coverage(spark, sf):
    """A5: a lattice of probe sites against the rows of pages."""
    probes = spark.range(4096).select("id", (F.call_function("div", F.col("id"), F.lit(64).cast("long")) * 262144).alias("x0"), (F.col("id") % 64 * 262144).alias("x1"))
    return measures.coverage(T.pages(spark, sf), probes, XY, 2_000_000)


Q38 = f"""WITH p AS (SELECT i AS id, i // 64 * 262144 AS x0, i % 64 * 262144 AS x1 FROM range(4096) t(i)), c AS ({C.PAGES}),
b AS (SELECT p.id, min((p.x0-c.x0)*(p.x0-c.x0)+(p.x1-c.x1)*(p.x1-c.x1)) AS d2 FROM p, c GROUP BY p.id)
SELECT 4096::BIGINT AS probes, count(*) FILTER (d2 < 4000000000000) AS covered, max(d2) FILTER (d2 < 4000000000000) AS worst_d2 FROM b"""


def q39_sep_64d(spark, sf):
    """A2 in 64 dimensions: pairs of embeddings nearer than a distance."""
    v = T.table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    return measures.separation(v, 1.15).select("a", "b", F.round("dist", 6).alias("dist"))


Q39 = """WITH v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS e FROM embeddings),
p AS (SELECT a.id AS a, b.id AS b, sqrt(list_sum(list_transform(range(1, 65), lambda i: (a.e[i] - b.e[i]) * (a.e[i] - b.e[i])))) AS dist FROM v a JOIN v b ON a.id < b.id)
SELECT a, b, round(dist, 6) AS dist FROM p WHERE dist < 1.15"""


def q40_halo(spark, sf):
    """Copies of the orders in every leaf within a gap."""
    cloud = T.orders(spark, sf)
    return rows.halo(cloud, _built(cloud, 2, 400, BITS[2]), XY, 200_000)


Q40 = f"""WITH {C.leaves(C.ORDERS, 2, 400, BITS[2])}, {C.boxes(2, BITS[2])}
SELECT p.id, b.cell AS target FROM pts p JOIN boxed b ON p.x0 >= b.lo0 - 200000 AND p.x0 < b.lo0 + b.side + 200000 AND p.x1 >= b.lo1 - 200000 AND p.x1 < b.lo1 + b.side + 200000"""


def q40b_halo_share(spark, sf):
    """Copies that halos of the orders' leaves add, over the rows themselves."""
    cloud = T.orders(spark, sf)
    all_ = rows.halo(cloud, _built(cloud, 2, 400, BITS[2]), XY, 200_000).agg(F.count("*").alias("held"))
    return all_.crossJoin(cloud.agg(F.count("*").alias("points"))).select("held", "points", F.round((F.col("held") - F.col("points")) / F.col("points"), 9).alias("share"))


Q40B = f"SELECT a.n AS held, b.n AS points, round((a.n - b.n) / b.n, 9) AS share FROM (SELECT count(*) AS n FROM ({Q40})) a, (SELECT count(*) AS n FROM ({C.ORDERS})) b"


def _generators(spark, sf):
    s = T.table(spark, sf, "supplier").select(F.col("s_suppkey").alias("id"))
    return s.select("id", (mix(F.col("id")) % (1 << 24)).alias("x0"), (mix(mix(F.col("id"))) % (1 << 24)).alias("x1"))


_GEN = f"SELECT s_suppkey AS id, {R.mix('s_suppkey')} % 16777216 AS x0, {R.mix(R.mix('s_suppkey'))} % 16777216 AS x1 FROM supplier"


def q41_voronoi_assign(spark, sf):
    """B2: the region of each customer is that of its nearest generator."""
    return rows.nearest_generator(T.customer(spark, sf), _generators(spark, sf), XY)


Q41 = f"""WITH c AS ({C.CUSTOMER}), g AS ({_GEN}), p AS (SELECT c.id, g.id AS gen, (c.x0-g.x0)*(c.x0-g.x0)+(c.x1-g.x1)*(c.x1-g.x1) AS d2 FROM c, g)
SELECT id, gen, d2 FROM p QUALIFY row_number() OVER (PARTITION BY id ORDER BY d2, gen) = 1"""


def q44_random(spark, sf):
    """Hashed uniform points in the disc, as many draws as customers."""
    return baselines.random_points(spark, D.disc(), T.table(spark, sf, "customer").count())


_RND = f"SELECT i AS id, {R.mix(R.mix('i + 17'))} % 16777216 AS x0, {R.mix(R.mix(R.mix('i + 1000003')))} % 16777216 AS x1 FROM range(0, (SELECT count(*) FROM customer)) t(i)"
_IN = f"(x0 - {CENTRE}) * (x0 - {CENTRE}) + (x1 - {CENTRE}) * (x1 - {CENTRE}) <= {RADIUS * RADIUS}"
Q44 = f"SELECT * FROM ({_RND}) WHERE {_IN}"


def q45_lattice_sq(spark, sf):
    """A square lattice in the disc at the spacing for the customer count."""
    return baselines.lattice(spark, D.disc(), size_h(T.table(spark, sf, "customer").count()), "square")


def q46_lattice_hex(spark, sf):
    """A hexagonal lattice."""
    return baselines.lattice(spark, D.disc(), size_h(T.table(spark, sf, "customer").count()), "hex")


_LAT = f"WITH h AS (SELECT {R.H2.format(n='count(*)')} AS h FROM customer), "
Q45 = _LAT + f"g AS (SELECT i * h AS x0, j * h AS x1 FROM h, range(0, 200) a(i), range(0, 200) b(j) WHERE i * h < 16777216 AND j * h < 16777216) SELECT x0, x1 FROM g WHERE {_IN}"
Q46 = _LAT + f"g AS (SELECT i * h + (j % 2) * (h // 2) AS x0, j * (h * 866026 // 1000000) AS x1 FROM h, range(0, 200) a(i), range(0, 240) b(j) WHERE i * h < 16777216 AND j * (h * 866026 // 1000000) < 16777216) SELECT x0, x1 FROM g WHERE {_IN}"


def q47_packing(spark, sf):
    """Random packing, hashed darts thinned by priority."""
    n = T.table(spark, sf, "customer").count()
    return baselines.random_packing(spark, D.disc(), 300_000, n)


Q47 = R.thinned(f"SELECT id, 300000::BIGINT AS h, x0, x1 FROM ({Q44})", 2)


def q59_domain_ops(spark, sf):
    """Membership of the events in combined regions, by event type."""
    poly = D.Polygon(((1_000_000, 0), (15_000_000, 100_000), (9_000_000, 3_000_000), (12_000_000, 9_000_000), (2_000_000, 6_000_000)))
    region = (poly | D.Ball((8_000_000, 1_000_000), 900_000)) - D.Box((4_000_000, 500_000), (5_000_000, 2_000_000))
    half = D.HalfSpace((1, 3), 14_000_000)
    e = T.events(spark, sf)
    return e.groupBy("grp").agg(F.sum(region.column(XY).cast("long")).alias("region"), F.sum((region & half).column(XY).cast("long")).alias("half"), F.sum(D.annulus((8_000_000, 0), 2_000_000, 5_000_000).column(XY).cast("long")).alias("ring"))


def _poly_sql():
    c = ((1_000_000, 0), (15_000_000, 100_000), (9_000_000, 3_000_000), (12_000_000, 9_000_000), (2_000_000, 6_000_000))
    hits = []
    for (x0, y0), (x1, y1) in zip(c, c[1:] + c[:1], strict=True):
        if y0 > y1:
            x0, y0, x1, y1 = x1, y1, x0, y0
        hits.append(f"(CASE WHEN x1 >= {y0} AND x1 < {y1} AND (x0 - {x0}) * {y1 - y0} < (x1 - {y0}) * ({x1 - x0}) THEN 1 ELSE 0 END)")
    return "((" + " + ".join(hits) + ") % 2 = 1)"


Q59 = f"""WITH e AS (SELECT *, ({_poly_sql()} OR (x0-8000000)*(x0-8000000)+(x1-1000000)*(x1-1000000) <= 810000000000) AND NOT (x0 BETWEEN 4000000 AND 5000000 AND x1 BETWEEN 500000 AND 2000000) AS r,
 (x0-8000000)*(x0-8000000)+x1*x1 AS q FROM ({C.EVENTS}))
SELECT grp, sum(r::INT)::BIGINT AS region, sum((r AND x0 + 3 * x1 <= 14000000)::INT)::BIGINT AS half, sum((q <= 25000000000000 AND q > 4000000000000)::INT)::BIGINT AS ring FROM e GROUP BY grp"""


def q60_candidates(spark, sf):
    """All candidates of the parts at one spacing."""
    return candidates(T.part(spark, sf).select("id", *XY).withColumn("h", F.lit(250_000).cast("long")), 2).select("id", "k", "c0", "c1")


_DX, _DY = R.direction_lists(2)
Q60 = f"""WITH p AS ({C.PART}), t AS (SELECT {_DX} AS dx, {_DY} AS dy)
SELECT id, k::INT AS k, ((x0 << 20) + 250003 * dx[{R.turn(2, 'x')} * 12 + k + 1] + 524288) >> 20 AS c0, ((x1 << 20) + 250003 * dy[{R.turn(2, 'x')} * 12 + k + 1] + 524288) >> 20 AS c1
FROM p, t, range(0, {directions(2).shape[1]}) r(k)"""


def q61_semi_in_domain(spark, sf):
    """M19 by table: orders in the cells that events occupy (semi-join)."""
    cells = T.events(spark, sf).select(tree.point_key(XY, 4).alias("cell"))
    return D.in_cells(T.orders(spark, sf), cells, XY, 4).select("id")


Q61 = f"SELECT id FROM ({C.ORDERS}) WHERE ((x0 >> 20) << 4) + (x1 >> 20) IN (SELECT ((x0 >> 20) << 4) + (x1 >> 20) FROM ({C.EVENTS}))"


def q62_anti_rejected(spark, sf):
    """Rejection as an anti-join: orders with no event nearer than a radius."""
    near = rows.within_pairs(T.events(spark, sf).select("id", *XY), T.orders(spark, sf).select("id", *XY), XY, 60_000, F.lit(60_000).cast("long")).select(F.col("b_id").alias("id")).distinct()
    return T.orders(spark, sf).select("id").join(near, "id", "left_anti")


Q62 = f"WITH e AS ({C.EVENTS}) SELECT id FROM ({C.ORDERS}) o WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.x0 BETWEEN o.x0 - 60000 AND o.x0 + 60000 AND (e.x0-o.x0)*(e.x0-o.x0)+(e.x1-o.x1)*(e.x1-o.x1) < 3600000000)"

QUERIES = {n: f for n, f in list(globals().items()) if n.startswith("q") and callable(f)}
_T = lambda cloud, h, d=2, **k: R.thinned(f"SELECT *, {h}::BIGINT AS h FROM ({cloud})", d, **k)
ORACLES = {
    "q31_thin_customer": _T(C.CUSTOMER, H31), "q32_thin_part": _T(C.PART, H32), "q33_thin_events": _T(C.EVENTS, Q33H), "q34_thin_embeddings": _T(C.embeddings(2), H34),
    "q34b_thin_embeddings_3d": _T(C.embeddings(3), 1_500_000, 3), "q35_thin_by_group": _T(C.CUSTOMER, 2_000_000, group="grp"),
    "q35b_thin_documents_by_lang": _T(C.DOCUMENTS, 30_000, group="grp"),
    "q35c_thin_labelled": R.thinned(f"SELECT id, x0, x1, quality::VARCHAR AS q, 60000::BIGINT AS h FROM ({C.DOCUMENTS}) JOIN labels ON doc_id = id", 2, group="q"),
    "q36_violations": Q36, "q37_nn_regularity": Q37, "q38_coverage": Q38, "q39_sep_64d": Q39, "q40_halo": Q40, "q40b_halo_share": Q40B, "q41_voronoi_assign": Q41, "q44_random": Q44,
    "q45_lattice_sq": Q45, "q46_lattice_hex": Q46, "q47_packing": Q47, "q59_domain_ops": Q59, "q60_candidates": Q60, "q61_semi_in_domain": Q61, "q62_anti_rejected": Q62,
}
