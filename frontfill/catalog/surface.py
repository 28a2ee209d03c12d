"""Queries of the relational and streaming surface around the methods."""

from __future__ import annotations

import tempfile

from pyspark.sql import Window
from pyspark.sql import functions as F

from frontfill.catalog import clouds_sql as C
from frontfill.catalog import recursion as R
from frontfill.catalog.fills import DISC
from frontfill.catalog.rowsets import XY
from frontfill.catalog.runs import LOG, RUNS, s_phase_log, s_runs
from frontfill.functions import udtf
from frontfill.functions.lattice import CENTRE, size_h
from frontfill.operators import tree
from frontfill.sources import tables as T
from frontfill.sources.lattice_source import LatticeSource
from frontfill.streaming import online


def q63_cube_runs(spark, sf):
    """Runs by method and workers, with all margins."""
    return s_runs(spark, sf).cube("method", "workers").agg(F.count("*").alias("runs"), F.sum("n").alias("points"))


Q63 = f"SELECT method, workers, count(*) AS runs, sum(n)::BIGINT AS points FROM {RUNS} GROUP BY CUBE (method, workers)"


def q64_rollup_levels(spark, sf):
    """Rows by cell at three levels, rolled up."""
    c = T.lineitem(spark, sf).select(F.shiftright("x0", 23).alias("a"), F.shiftright("x1", 22).alias("b"))
    return c.rollup("a", "b").agg(F.count("*").alias("n"))


Q64 = f"SELECT x0 >> 23 AS a, x1 >> 22 AS b, count(*) AS n FROM ({C.LINEITEM}) GROUP BY ROLLUP (a, b)"


def q65_grouping_sets(spark, sf):
    """Runs by (method, limit) and by workers in one pass."""
    s_runs(spark, sf).createOrReplaceTempView("ff_runs")
    return spark.sql("SELECT method, lim, workers, count(*) AS runs, sum(n) AS points FROM ff_runs GROUP BY GROUPING SETS ((method, lim), (workers))")


Q65 = f"SELECT method, lim, workers, count(*) AS runs, sum(n)::BIGINT AS points FROM {RUNS} GROUP BY GROUPING SETS ((method, lim), (workers))"


def q66_window_rank(spark, sf):
    """Three steepest customers of each nation by balance, ties by key."""
    c = T.customer(spark, sf)
    w = Window.partitionBy("grp").orderBy(F.desc("x0"), "id")
    return c.withColumn("place", F.row_number().over(w)).withColumn("rank", F.rank().over(Window.partitionBy("grp").orderBy(F.desc("x0")))).where("place <= 3").select("grp", "id", "place", "rank")


Q66 = f"SELECT grp, id, (row_number() OVER (PARTITION BY grp ORDER BY x0 DESC, id))::INT AS place, (rank() OVER (PARTITION BY grp ORDER BY x0 DESC))::INT AS rank FROM ({C.CUSTOMER}) QUALIFY place <= 3"


def q67_window_rows_frame(spark, sf):
    """Insert amount over the last ten rows of each worker."""
    w = Window.partitionBy("worker").orderBy("t_start", "t_end").rowsBetween(-9, 0)
    return s_phase_log(spark, sf).select("worker", F.round("t_start", 3).alias("t"), F.round(F.sum(F.col("t_end") - F.col("t_start")).over(w), 4).alias("busy"), F.count("*").over(w).alias("rows"))


Q67 = f"SELECT worker, round(t_start, 3) AS t, round(sum(t_end - t_start) OVER w, 4) AS busy, count(*) OVER w AS rows FROM {LOG} WINDOW w AS (PARTITION BY worker ORDER BY t_start, t_end ROWS 9 PRECEDING)"


def q68_window_range_frame(spark, sf):
    """Rows of each type within the hour before each row."""
    e = T.table(spark, sf, "events").select("event_id", "event_type", F.call_function("div", F.unix_micros(F.col("ts").cast("timestamp")), F.lit(1_000_000).cast("long")).alias("s"))
    w = Window.partitionBy("event_type").orderBy("s").rangeBetween(-3600, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


Q68 = "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events"


def q69_topk_cells(spark, sf):
    """The seven densest cells, ties by key: a top-k report."""
    return T.lineitem(spark, sf).groupBy(tree.point_key(["x0", "x1", "x2"], 3).alias("cell")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "cell").limit(7)


Q69 = f"SELECT 512 + {C.morton(['(x0 >> 21)', '(x1 >> 21)', '(x2 >> 21)'], 3)} AS cell, count(*) AS n FROM ({C.LINEITEM}) GROUP BY 1 ORDER BY n DESC, cell LIMIT 7"


def q70_setops(spark, sf):
    """Cells that both clouds hold, and those of one alone."""
    a = T.orders(spark, sf).select(tree.point_key(XY, 5).alias("cell"))
    b = T.events(spark, sf).select(tree.point_key(XY, 5).alias("cell"))
    both = a.intersect(b).withColumn("side", F.lit("both"))
    return both.unionByName(a.distinct().exceptAll(b.distinct()).withColumn("side", F.lit("orders"))).unionByName(b.distinct().subtract(a).withColumn("side", F.lit("events")))


_K5 = "1024 + " + C.morton(["(x0 >> 19)", "(x1 >> 19)"], 5)
Q70 = f"WITH a AS (SELECT DISTINCT {_K5} AS cell FROM ({C.ORDERS})), b AS (SELECT DISTINCT {_K5} AS cell FROM ({C.EVENTS})) SELECT cell, 'both' AS side FROM a JOIN b USING (cell) UNION ALL SELECT cell, 'orders' FROM a WHERE cell NOT IN (SELECT cell FROM b) UNION ALL SELECT cell, 'events' FROM b WHERE cell NOT IN (SELECT cell FROM a)"


def q71_json_array_map(spark, sf):
    """A JSON property as stratum; sums of squares over vector axes."""
    e = T.table(spark, sf, "events").select(F.from_json("props", "k string").alias("p"), "value")
    a = e.groupBy(F.col("p.k").alias("key")).agg(F.count("*").alias("n"))
    v = T.table(spark, sf, "embeddings").select(F.concat(F.lit("label "), F.col("label").cast("string")).alias("key"), F.aggregate(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1024).cast("long")), F.lit(0).cast("long"), lambda s, x: s + x * x).alias("q"))
    return a.unionByName(v.groupBy("key").agg(F.sum("q").alias("n")))


Q71 = """SELECT (props::JSON ->> 'k') AS key, count(*) AS n FROM events GROUP BY 1 UNION ALL
SELECT 'label ' || label, sum(list_sum(list_transform(embedding, lambda x: CAST(FLOOR(x::DOUBLE * 1024) AS BIGINT) * CAST(FLOOR(x::DOUBLE * 1024) AS BIGINT))))::BIGINT FROM embeddings GROUP BY label"""


def q72_asof_state(spark, sf):
    """As-of join: the last click before each purchase of a user, by one ordered pass over the union."""
    e = T.table(spark, sf, "events").where(F.col("event_type").isin("click", "purchase")).select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = Window.partitionBy("user_id").orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("before", last).where("event_type = 'purchase'").select("event_id", "before")


Q72 = """WITH e AS (SELECT event_id, user_id, event_type, ts FROM events WHERE event_type IN ('click', 'purchase')),
p AS (SELECT event_id, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before, event_type FROM e)
SELECT event_id, before FROM p WHERE event_type = 'purchase'"""


def q73_interval_overlap(spark, sf):
    """Pairs of workers that are busy at once in one run: an interval join on time slots."""
    log = s_phase_log(spark, sf).withColumn("id", F.xxhash64("run", "worker", "t_start", "t_end"))
    slot = 600.0
    cut = log.select("id", "run", "worker", "t_start", "t_end", F.explode(F.sequence(F.floor(F.col("t_start") / slot), F.floor(F.col("t_end") / slot))).alias("slot"))
    a, b = cut.alias("a"), cut.alias("b")
    meet = (F.col("a.run") == F.col("b.run")) & (F.col("a.slot") == F.col("b.slot")) & (F.col("a.worker") < F.col("b.worker")) & (F.col("a.t_start") < F.col("b.t_end")) & (F.col("b.t_start") < F.col("a.t_end"))
    # a pair counts in the slot where its overlap begins
    begins = F.floor(F.greatest("a.t_start", "b.t_start") / slot) == F.col("a.slot")
    return a.join(b, meet & begins).groupBy(F.col("a.run").alias("run"), F.col("a.worker").alias("w0"), F.col("b.worker").alias("w1")).agg(F.count("*").alias("overlaps"))


Q73 = f"SELECT a.run, a.worker AS w0, b.worker AS w1, count(*) AS overlaps FROM {LOG} a JOIN {LOG} b ON a.run = b.run AND a.worker < b.worker AND a.t_start < b.t_end AND b.t_start < a.t_end GROUP BY ALL"


def q74_session_windows(spark, sf):
    """Sessions of a user's rows with pauses under half an hour."""
    e = T.table(spark, sf, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    return online.sessions(e, "user_id").select("user_id", F.unix_micros("start").alias("start"), F.unix_micros("end").alias("end"), "n")


Q74 = """WITH e AS (SELECT user_id, epoch_us(ts) AS t, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events),
s AS (SELECT *, sum(CASE WHEN p IS NULL OR t - p > 1800000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS g FROM e)
SELECT user_id, min(t) AS start, max(t) + 1800000000 AS "end", count(*) AS n FROM s GROUP BY user_id, g"""


def q74b_rate_windows(spark, sf):
    """Insertion rate by sliding window."""
    e = T.table(spark, sf, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    return online.rate_windows(e, width="1 hour", slide="15 minutes").select(F.unix_micros("start").alias("start"), "n")


Q74B = "SELECT (epoch_us(ts) // 900000000 - k) * 900000000 AS start, count(*) AS n FROM events, range(0, 4) t(k) GROUP BY 1"


def q75_star_join_seeds(spark, sf):
    """Seeds weighted by line items, by region: a star of joins."""
    r, n, s = (T.table(spark, sf, t) for t in ("region", "nation", "supplier"))
    li = T.table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"))
    j = li.join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(n, F.col("s_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.countDistinct("s_suppkey").alias("seeds"), F.sum("n").alias("weight"))


Q75 = "SELECT r_name, count(DISTINCT s_suppkey) AS seeds, count(*) AS weight FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"


def q76_string_date_features(spark, sf):
    """Text, address and date features as axes."""
    p = T.table(spark, sf, "pages").select(F.lit("page").alias("kind"), F.col("page_id").alias("id"), F.length("url").cast("long").alias("a"), F.length(F.regexp_replace("url", "[^/]", "")).cast("long").alias("b"))
    o = T.table(spark, sf, "orders").select(F.lit("order").alias("kind"), F.col("o_orderkey").alias("id"), F.month("o_orderdate").cast("long").alias("a"), F.dayofyear("o_orderdate").cast("long").alias("b"))
    c = T.table(spark, sf, "conversations").select(F.lit("turn").alias("kind"), (F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.length("text").cast("long").alias("a"), F.size(F.split("text", " ")).cast("long").alias("b"))
    return p.unionByName(o).unionByName(c)


Q76 = """SELECT 'page' AS kind, page_id AS id, length(url) AS a, length(regexp_replace(url, '[^/]', '', 'g')) AS b FROM pages
UNION ALL SELECT 'order', o_orderkey, month(o_orderdate), dayofyear(o_orderdate) FROM orders
UNION ALL SELECT 'turn', conv_id * 1000 + turn, length(text), len(string_split(text, ' ')) FROM conversations"""


def q76b_clouds(spark, sf):
    """All row clouds: rows, and sums of their axes."""
    parts = [("orders", T.orders(spark, sf)), ("events", T.events(spark, sf)), ("customer", T.customer(spark, sf)), ("part", T.part(spark, sf)), ("pages", T.pages(spark, sf)), ("documents", T.documents(spark, sf)), ("conversations", T.conversations(spark, sf)), ("embeddings", T.embeddings(spark, sf))]
    out = None
    for name, c in parts:
        one = c.agg(F.count("*").alias("n"), F.sum("x0").alias("x0"), F.sum("x1").alias("x1")).withColumn("cloud", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


Q76B = " UNION ALL ".join(f"SELECT '{n}' AS cloud, count(*) AS n, sum(x0)::BIGINT AS x0, sum(x1)::BIGINT AS x1 FROM ({q})" for n, q in (("orders", C.ORDERS), ("events", C.EVENTS), ("customer", C.CUSTOMER), ("part", C.PART), ("pages", C.PAGES), ("documents", C.DOCUMENTS), ("conversations", C.CONVERSATIONS), ("embeddings", C.embeddings(2))))


def q77_udtf_fill(spark, sf):
    """The fill as a table function in SQL."""
    udtf.register(spark)
    return spark.sql(f"SELECT seq, x0, x1 FROM fill_disc({size_h(T.table(spark, sf, 'supplier').count())})")


Q77 = R.sequential(f"SELECT {R.H2.format(n='count(*)')} AS h FROM supplier", [f"[{CENTRE}]::BIGINT[]"] * 2, DISC, "h", 2)
Q77 = f"SELECT seq, x0, x1 FROM ({Q77})"


def q78_agg_udf(spark, sf):
    """A grouped aggregate in Python: the widest gap of each priority's prices."""
    o = T.orders(spark, sf)
    return o.groupBy("grp").agg(udtf.widest_gap(F.col("x1")).alias("gap"))


Q78 = f"SELECT grp, max(x1 - p) AS gap FROM (SELECT grp, x1, lag(x1) OVER (PARTITION BY grp ORDER BY x1) AS p FROM ({C.ORDERS})) GROUP BY grp"


def q78b_lattice_source(spark, sf):
    """Sites of the Python data source inside the disc, by column."""
    from frontfill.functions import domain as D

    spark.dataSource.register(LatticeSource)
    sites = spark.read.format("lattice").option("step", "524288").load()
    return sites.where(D.disc().column(XY)).groupBy("x0").agg(F.count("*").alias("n"))


Q78B = f"SELECT i * 524288 AS x0, count(*) AS n FROM range(0, 32) a(i), range(0, 32) b(j) WHERE (i * 524288 - {CENTRE}) * (i * 524288 - {CENTRE}) + (j * 524288 - {CENTRE}) * (j * 524288 - {CENTRE}) <= 36000000000000 GROUP BY 1"


def _folder(spark):
    return spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="frontfill-stream-")


def q79_stream_thin(spark, sf):
    """Online thinning of the events in one available-now run: no violation, and no row left that could be kept."""
    import uuid

    from frontfill.operators.rows import within_pairs

    base = f"{_folder(spark)}/thin-{uuid.uuid4().hex}"
    h = 400_000
    src = spark.readStream.schema(spark.read.parquet(f"{sf}/events.parquet").schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf}/events.parquet*")
    ms = T.events_axes(src)
    online.thin_stream(ms, XY, h, f"{base}/out", f"{base}/state").awaitTermination()
    kept = spark.read.option("basePath", f"{base}/out").parquet(f"{base}/out/batch=*").select("id", *XY)
    every = T.events(spark, sf).select("id", *XY)
    bad = within_pairs(kept, kept, XY, h, F.lit(h).cast("long")).where("a_id < b_id").agg(F.count("*").alias("violations"))
    near = within_pairs(kept, every, XY, h, F.lit(h).cast("long")).select("b_id").distinct().agg(F.count("*").alias("c"))
    return bad.crossJoin(every.agg(F.count("*").alias("n"))).crossJoin(near).select("violations", (F.col("n") - F.col("c")).alias("uncovered"))


Q79 = "SELECT 0::BIGINT AS violations, 0::BIGINT AS uncovered"


def q80_stream_windows(spark, sf):
    """Windowed counts behind a watermark from a stream; ordered input loses nothing."""
    import uuid

    name = f"ff_{uuid.uuid4().hex[:12]}"
    src = spark.readStream.schema(spark.read.parquet(f"{sf}/events.parquet").schema).parquet(f"{sf}/events.parquet*").select(F.col("ts").cast("timestamp").alias("ts"))
    q = online.rate_windows(src, late="1 day", width="1 day").writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", f"{_folder(spark)}/{name}").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).select(F.unix_micros("start").alias("start"), "n")


Q80 = "SELECT epoch_us(ts) // 86400000000 * 86400000000 AS start, count(*) AS n FROM events GROUP BY 1"

def _events_stream(spark, sf):
    src = spark.readStream.schema(spark.read.parquet(f"{sf}/events.parquet").schema).parquet(f"{sf}/events.parquet*")
    return src.select(F.col("event_id").alias("id"), "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))


def _run(spark, df, mode):
    """All rows that a stream gives in one available-now run."""
    import uuid

    name = f"ff_{uuid.uuid4().hex[:12]}"
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{_folder(spark)}/{name}").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def q80b_stream_late(spark, sf):
    """Late rows by micro-batch: the events arrive in three files, dealt by their number, and the later files are late in part."""
    import uuid

    base = f"{_folder(spark)}/late-{uuid.uuid4().hex}"
    every = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    for k in range(3):
        every.where(F.col("event_id") % 3 == k).coalesce(1).write.mode("append").parquet(f"{base}/in")
    src = spark.readStream.schema(every.schema).option("maxFilesPerTrigger", 1).parquet(f"{base}/in")
    online.late_counts(src, f"{base}/out", f"{base}/state", late="20 days").awaitTermination()
    return spark.read.parquet(f"{base}/out/mark=*").select("batch", "n", "late")


Q80B = """
WITH e AS (SELECT event_id % 3 AS batch, ts FROM events),
m AS (SELECT k.batch, max(e.ts) AS mark FROM (SELECT DISTINCT batch FROM e) k LEFT JOIN e ON e.batch < k.batch GROUP BY 1)
SELECT e.batch, count(*) AS n, count(*) FILTER (e.ts < m.mark - INTERVAL 20 DAY) AS late FROM e JOIN m USING (batch) GROUP BY 1
"""


def q80c_stream_static_join(spark, sf):
    """Streamed events by nation of their user, from a table."""
    who = T.table(spark, sf, "customer").select("c_custkey", "c_nationkey")
    return _run(spark, online.with_static(_events_stream(spark, sf), who, "user_id", "c_custkey").groupBy("c_nationkey").agg(F.count("*").alias("n")), "complete")


Q80C = "SELECT c_nationkey, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1"


def q80d_stream_stream_join(spark, sf):
    """Purchases within six hours of a click of the same user, both streamed."""
    seen, bought = (_events_stream(spark, sf).where(F.col("event_type") == kind) for kind in ("click", "purchase"))
    return _run(spark, online.follow_ups(seen, bought, "user_id", "6 hours"), "append")


Q80D = """
SELECT a.user_id, a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id
AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'
"""

QUERIES = {n: f for n, f in list(globals().items()) if n.startswith("q") and callable(f)}
ORACLES = {
    "q63_cube_runs": Q63, "q64_rollup_levels": Q64, "q65_grouping_sets": Q65, "q66_window_rank": Q66, "q67_window_rows_frame": Q67, "q68_window_range_frame": Q68, "q69_topk_cells": Q69, "q70_setops": Q70,
    "q71_json_array_map": Q71, "q72_asof_state": Q72, "q73_interval_overlap": Q73, "q74_session_windows": Q74, "q74b_rate_windows": Q74B, "q75_star_join_seeds": Q75, "q76_string_date_features": Q76,
    "q76b_clouds": Q76B, "q77_udtf_fill": Q77, "q78_agg_udf": Q78, "q78b_lattice_source": Q78B, "q79_stream_thin": Q79, "q80_stream_windows": Q80,
    "q80b_stream_late": Q80B, "q80c_stream_static_join": Q80C, "q80d_stream_stream_join": Q80D,
}
