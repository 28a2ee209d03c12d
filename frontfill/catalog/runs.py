"""Queries of the run-log measures, on logs derived from orders and events."""

from __future__ import annotations

from pyspark.sql import functions as F

from frontfill.operators import runlog
from frontfill.sources import tables as T


def s_runs(spark, sf):
    o = T.table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderpriority")
    k = F.col("o_orderkey")
    t = F.col("o_totalprice") / 1000.0
    w = F.expr("shiftleft(1, cast(substring(o_orderpriority, 1, 1) as int) - 1)")
    return o.select(
        k.cast("string").alias("run"), F.col("o_orderstatus").alias("method"), (F.col("o_custkey") % 2).alias("h"), (50 * (1 + k % 3)).alias("lim"), w.alias("workers"), (k % 10).cast("int").alias("realisation"),
        (1000 + k % 500).alias("n"), t.alias("fill_s"), (t * (k % 7) / 100.0).alias("prebuild_s"), (t * (0.9 + (k % 10) / 100.0)).alias("first_stage_s"), (t * w * (k % 5 + 5) / 10.0).alias("active_s"),
    )


def s_phase_log(spark, sf):
    e = T.table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type", "value")
    t = (F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(1_704_067_200_000_000)) / 1e6
    return e.select((F.col("event_id") % 3).cast("string").alias("run"), F.when(F.col("event_type") == "click", 2).otherwise(1).alias("stage"), (F.col("user_id") % 7).cast("int").alias("worker"), t.alias("t_start"), (t + F.col("value")).alias("t_end"))


RUNS = """(SELECT o_orderkey::VARCHAR AS run, o_orderstatus AS method, o_custkey % 2 AS h, 50 * (1 + o_orderkey % 3) AS lim, (1 << (o_orderpriority[1]::INT - 1))::INT AS workers,
 1000 + o_orderkey % 500 AS n, o_totalprice / 1000.0::DOUBLE AS fill_s, o_totalprice / 1000.0::DOUBLE * (o_orderkey % 7) / 100.0::DOUBLE AS prebuild_s, o_orderkey AS k FROM orders)"""
LOG = """(SELECT (event_id % 3)::VARCHAR AS run, CASE WHEN event_type = 'click' THEN 2 ELSE 1 END AS stage, (user_id % 7)::INT AS worker,
 (epoch_us(ts) - 1704067200000000)::DOUBLE / 1e6 AS t_start, (epoch_us(ts) - 1704067200000000)::DOUBLE / 1e6 + value AS t_end FROM events)"""
_R = lambda df, *cols: df.withColumns({c: F.round(c, 6) for c in cols})


def q51_throughput_efficiency(spark, sf):
    """A7, A8."""
    return _R(runlog.efficiency(s_runs(spark, sf)), "rate", "per_worker", "efficiency")


Q51 = f"""WITH m AS (SELECT method, h, workers, avg(n / fill_s) AS rate FROM {RUNS} GROUP BY ALL), o AS (SELECT method, h, rate AS one FROM m WHERE workers = 1)
SELECT method, h, workers, round(rate, 6) AS rate, round(rate / workers, 6) AS per_worker, round(rate / workers / one, 6) AS efficiency FROM m LEFT JOIN o USING (method, h)"""


def q52_relative(spark, sf):
    """One method over another at equal workers and size."""
    return _R(runlog.relative(s_runs(spark, sf), "O", "F"), "relative")


Q52 = f"SELECT h, workers, round(avg(n / fill_s) FILTER (method = 'F') / avg(n / fill_s) FILTER (method = 'O'), 6) AS relative FROM {RUNS} GROUP BY h, workers"


def q53_activity(spark, sf):
    """A10."""
    return _R(runlog.activity(s_phase_log(spark, sf)), "busy", "span", "active")


Q53 = f"WITH x AS (SELECT run, count(DISTINCT worker) AS workers, sum(t_end - t_start) AS busy, max(t_end) - min(t_start) AS span FROM {LOG} GROUP BY run) SELECT run, workers, round(busy, 6) AS busy, round(span, 6) AS span, round(busy / (workers * span), 6) AS active FROM x"


def q54_stage_share(spark, sf):
    """A11, A21."""
    return _R(runlog.stage_share(s_phase_log(spark, sf)), "stage1")


Q54 = f"SELECT run, round(sum(CASE WHEN stage = 1 THEN t_end - t_start ELSE 0 END) / sum(t_end - t_start), 6) AS stage1, max(stage) AS stages FROM {LOG} GROUP BY run"


def q55_sensitivity(spark, sf):
    """A15."""
    return _R(runlog.sensitivity(s_runs(spark, sf)), "rate", "spread")


Q55 = f"WITH m AS (SELECT h, workers, lim, avg(n / fill_s) AS rate FROM {RUNS} GROUP BY ALL) SELECT h, workers, lim, round(rate, 6) AS rate, round(max(rate) OVER w / min(rate) OVER w, 6) AS spread FROM m WINDOW w AS (PARTITION BY h, workers)"


def q55b_prebuild(spark, sf):
    """A16."""
    return _R(runlog.prebuild_share(s_runs(spark, sf)), "share", "scaled")


Q55B = f"SELECT method, workers, round(sum(prebuild_s) / sum(fill_s), 6) AS share, round(sum(prebuild_s / workers) / sum(fill_s), 6) AS scaled FROM {RUNS} GROUP BY ALL"


def q55c_summary(spark, sf):
    """Means with their samples kept (here their number and extremes)."""
    s = runlog.summarise(s_runs(spark, sf))
    return _R(s, "rate", "spread").select("method", "h", "workers", "lim", "samples", "rate", "spread", F.element_at("each", 1).alias("least"), F.element_at("each", -1).alias("most"))


Q55C = f"SELECT method, h, workers, lim, count(*) AS samples, round(avg(n / fill_s), 6) AS rate, round(stddev_pop(n / fill_s), 6) AS spread, round(min(n / fill_s), 6) AS least, round(max(n / fill_s), 6) AS most FROM {RUNS} GROUP BY ALL"


def q56_bifurcation(spark, sf):
    """A18."""
    return _R(runlog.bifurcation(s_runs(spark, sf)), "low", "high", "ratio")


Q56 = f"""WITH x AS (SELECT method, h, workers, run, n / fill_s AS rate FROM {RUNS}),
y AS (SELECT *, row_number() OVER w AS i, sum(rate) OVER (PARTITION BY method, h, workers ORDER BY rate, run ROWS UNBOUNDED PRECEDING) AS s, count(*) OVER p AS n, sum(rate) OVER p AS t FROM x
  WINDOW w AS (PARTITION BY method, h, workers ORDER BY rate, run), p AS (PARTITION BY method, h, workers)),
z AS (SELECT *, s / i AS low, (t - s) / (n - i) AS high, round(s * s / i + (t - s) * (t - s) / (n - i), 6) AS g FROM y WHERE i < n)
SELECT method, h, workers, i AS in_low, n - i AS in_high, round(low, 6) AS low, round(high, 6) AS high, round(high / low, 6) AS ratio FROM z QUALIFY row_number() OVER (PARTITION BY method, h, workers ORDER BY g DESC, i) = 1"""


def q57_growth(spark, sf):
    """Log-log slope by return flag."""
    return _R(runlog.growth(T.table(spark, sf, "lineitem").select("l_returnflag", "l_quantity", "l_extendedprice"), "l_quantity", "l_extendedprice", "l_returnflag"), "slope")


Q57 = "SELECT l_returnflag, round(regr_slope(ln(l_extendedprice), ln(l_quantity)), 6) AS slope FROM lineitem GROUP BY 1"


def q57b_lock_summary(spark, sf):
    """Synchronisation events a method and kind, and for each insert."""
    r = s_runs(spark, sf).select("method", F.when(F.col("lim") == 50, "claim").when(F.col("lim") == 100, "release").otherwise("enqueue").alias("kind"), F.col("workers").cast("long").alias("n"), F.col("n").alias("inserts"))
    return _R(runlog.lock_summary(r), "per_insert")


Q57B = f"SELECT method, CASE lim WHEN 50 THEN 'claim' WHEN 100 THEN 'release' ELSE 'enqueue' END AS kind, sum(workers)::BIGINT AS events, round(sum(workers) / sum(n), 6) AS per_insert FROM {RUNS} GROUP BY ALL"

QUERIES = {n: f for n, f in list(globals().items()) if n.startswith("q") and callable(f)}
ORACLES = {
    "q51_throughput_efficiency": Q51, "q52_relative": Q52, "q53_activity": Q53, "q54_stage_share": Q54, "q55_sensitivity": Q55, "q55b_prebuild": Q55B, "q55c_summary": Q55C,
    "q56_bifurcation": Q56, "q57_growth": Q57, "q57b_lock_summary": Q57B,
}
