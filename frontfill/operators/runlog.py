"""Measures over run logs and phase logs: throughput, efficiency, activity, stages, sensitivity, bifurcation, growth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def throughput(runs: DataFrame) -> DataFrame:
    """Points a second, prebuilding excluded."""
    return runs.withColumn("rate", F.col("n") / F.col("fill_s"))


def efficiency(runs: DataFrame) -> DataFrame:
    """``method, h, workers, rate, per_worker, efficiency``: mean rate, rate a worker, and that over the rate of one worker."""
    mean = throughput(runs).groupBy("method", "h", "workers").agg(F.avg("rate").alias("rate"))
    one = mean.where("workers = 1").select("method", "h", F.col("rate").alias("one"))
    return mean.join(one, ["method", "h"], "left").select("method", "h", "workers", "rate", (F.col("rate") / F.col("workers")).alias("per_worker"), (F.col("rate") / F.col("workers") / F.col("one")).alias("efficiency"))


def relative(runs: DataFrame, method: str, baseline: str) -> DataFrame:
    """Baseline rate over the method's at equal workers and spacing."""
    p = throughput(runs).groupBy("h", "workers").pivot("method", [method, baseline]).agg(F.avg("rate"))
    return p.select("h", "workers", (F.col(baseline) / F.col(method)).alias("relative"))


def activity(log: DataFrame) -> DataFrame:
    """Share of worker time that is busy: ``run, workers, busy, span, active``."""
    x = log.groupBy("run").agg(F.countDistinct("worker").alias("workers"), F.sum(F.col("t_end") - F.col("t_start")).alias("busy"), (F.max("t_end") - F.min("t_start")).alias("span"))
    return x.withColumn("active", F.col("busy") / (F.col("workers") * F.col("span")))


def stage_share(log: DataFrame) -> DataFrame:
    """Share of busy time that falls in the first stage."""
    busy = F.col("t_end") - F.col("t_start")
    return log.groupBy("run").agg((F.sum(F.when(F.col("stage") == 1, busy).otherwise(0.0)) / F.sum(busy)).alias("stage1"), F.max("stage").alias("stages"))


def sensitivity(runs: DataFrame) -> DataFrame:
    """Mean rate for each limit, and the ratio of the best limit's to the worst's at equal workers and size."""
    m = throughput(runs).groupBy("h", "workers", "lim").agg(F.avg("rate").alias("rate"))
    w = Window.partitionBy("h", "workers")
    return m.withColumn("spread", F.max("rate").over(w) / F.min("rate").over(w))


def prebuild_share(runs: DataFrame) -> DataFrame:
    """Prebuild time over fill time, as measured and if it scaled perfectly."""
    return runs.groupBy("method", "workers").agg((F.sum("prebuild_s") / F.sum("fill_s")).alias("share"), (F.sum(F.col("prebuild_s") / F.col("workers")) / F.sum("fill_s")).alias("scaled"))


def summarise(runs: DataFrame) -> DataFrame:
    """Mean and spread over realisations, samples kept."""
    return throughput(runs).groupBy("method", "h", "workers", "lim").agg(F.count("*").alias("samples"), F.avg("rate").alias("rate"), F.stddev_pop("rate").alias("spread"), F.array_sort(F.collect_list(F.round("rate", 6))).alias("each"))


def bifurcation(runs: DataFrame, keys: tuple[str, ...] = ("method", "h", "workers")) -> DataFrame:
    """Best split of each configuration's rates into two clusters, by least squares: sizes, means and their ratio."""
    rate = throughput(runs)
    w = Window.partitionBy(*keys).orderBy("rate", "run")
    every = Window.partitionBy(*keys)
    x = rate.select(*keys, "run", "rate").withColumns({"i": F.row_number().over(w), "s": F.sum("rate").over(w.rowsBetween(Window.unboundedPreceding, 0)), "n": F.count("*").over(every), "t": F.sum("rate").over(every)})
    x = x.where(F.col("i") < F.col("n"))
    low, high = F.col("s") / F.col("i"), (F.col("t") - F.col("s")) / (F.col("n") - F.col("i"))
    gain = F.round(low * F.col("s") + high * (F.col("t") - F.col("s")), 6)
    best = x.groupBy(*keys).agg(F.max(F.struct(gain.alias("g"), (-F.col("i")).alias("m"), low.alias("low"), high.alias("high"), "n")).alias("b"))
    return best.select(*keys, (-F.col("b.m")).cast("long").alias("in_low"), (F.col("b.n") + F.col("b.m")).cast("long").alias("in_high"), F.col("b.low").alias("low"), F.col("b.high").alias("high"), (F.col("b.high") / F.col("b.low")).alias("ratio"))


def growth(points: DataFrame, n: str, t: str, *keys: str) -> DataFrame:
    """Slope of log t over log n: 1 for cost in proportion."""
    return points.groupBy(*keys).agg(F.regr_slope(F.ln(t), F.ln(n)).alias("slope"))


def lock_summary(log: DataFrame) -> DataFrame:
    """Synchronisation events by kind, and for each insert: ``lock_log(method, kind, n, inserts)``."""
    return log.groupBy("method", "kind").agg(F.sum("n").alias("events"), (F.sum("n") / F.sum("inserts")).alias("per_insert"))
