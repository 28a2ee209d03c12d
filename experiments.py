"""Runs the experiment workloads and prints their tables: ``python experiments.py [N] [realisations]``.

``python experiments.py scaling [N] [realisations]`` measures strong scaling in seconds: the fill by blocks and seams on 1, 2, 4 and 8 cores and
the baseline in one task, each core count in a process of its own.
"""

from __future__ import annotations

import json
import os
import statistics
import subprocess
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from frontfill.functions import domain as D  # noqa: E402
from frontfill.functions import spacing as S  # noqa: E402
from frontfill.functions.lattice import size_h  # noqa: E402
from frontfill.plans import baselines, seams  # noqa: E402
from frontfill.plans import workloads as W  # noqa: E402
from frontfill.sources.store import stored  # noqa: E402


def main(n: int = 37_500, realisations: int = 3) -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", "16").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    show = lambda title, df: (print(f"\n## {title}"), df.show(200, False))
    show("W0 density", W.w0_density(spark))
    show("W1 snapshot", W.w1_snapshot(spark).groupBy("owner").agg(F.count("*").alias("cells"), F.sum("n").alias("points")).orderBy("owner"))
    runs = stored(W.w2_limits(spark, n, workers=(8, 32), realisations=realisations))
    show("W2 limits", runs.groupBy("workers", "lim").agg(F.avg("n").alias("n"), F.avg("supersteps").alias("supersteps"), F.avg("active").alias("active"), F.avg(F.col("attempts") / F.col("n")).alias("claims_per_point"), F.avg("stages").alias("stages")).orderBy("workers", "lim"))
    runs = stored(W.w3_scaling(spark, (n, 16 * n), realisations=realisations))
    speed = runs.groupBy("h", "workers").agg(F.avg("n").alias("n"), F.avg(F.col("n") / F.col("supersteps")).alias("points_per_step"), F.avg("stages").alias("stages"), F.avg(F.col("attempts") / F.col("n")).alias("claims_per_point"))
    one = speed.where("workers = 1").select("h", F.col("points_per_step").alias("one"))
    show("W3 scaling", speed.join(one, "h").withColumn("efficiency", F.col("points_per_step") / F.col("workers") / F.col("one")).drop("one").orderBy("h", "workers"))
    show("W4 share of the first stage", W.w4_stage_share(runs).orderBy("h", "workers"))
    show("W5 activity", W.w5_activity(runs).orderBy("h", "workers"))
    show("W6 prebuild", W.w6_prebuild(spark, n))
    show("W7 clusters of realisations", W.w7_bifurcation(runs).orderBy("h", "workers"))
    show("W12 membership", W.w12_membership(spark, n))
    show("locks", W.locks(spark, n))


def measure(cores: int, n: int, realisations: int) -> None:
    """One JSON line a realisation: points and seconds on so many cores; realisations differ in their spacing by one part in a thousand."""
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", str(2 * cores)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    seams.fill_seams(spark, D.disc(), S.Constant(size_h(n // 8)), block_points=max(500, n // 256)).count()
    for r in range(realisations):
        h = S.Constant(size_h(n) + size_h(n) * r // 1000)
        # the same blocks on every number of cores, so that the work is the same
        runs = {"seams": lambda h=h: seams.fill_seams(spark, D.disc(), h, block_points=max(2000, n // 32))}
        if cores == 1:
            runs["baseline"] = lambda h=h: baselines.voronoi_kd_fill(spark, D.disc(), h, 32)
        for method, run in runs.items():
            t = time.perf_counter()
            points = run().count()
            print(json.dumps({"method": method, "cores": cores, "points": points, "seconds": round(time.perf_counter() - t, 3)}), flush=True)
    spark.stop()


def scaling(n: int = 150_000, realisations: int = 5) -> None:
    """Median points a second by cores, and efficiency against one core."""
    rates: dict[tuple[str, int], list[float]] = {}
    for cores in (1, 2, 4, 8):
        out = subprocess.run([sys.executable, __file__, "measure", str(cores), str(n), str(realisations)], stdout=subprocess.PIPE, check=True, text=True).stdout
        for row in (json.loads(line) for line in out.splitlines() if line.startswith("{")):
            rates.setdefault((row["method"], row["cores"]), []).append(row["points"] / row["seconds"])
    one = statistics.median(rates["seams", 1])
    for (method, cores), r in sorted(rates.items()):
        mid = statistics.median(r)
        print(f"{method:10s} cores {cores}  points/s {mid:9.0f}  least {min(r):9.0f}  most {max(r):9.0f}  realisations {len(r)}  of one core x cores {mid / one / cores:5.2f}")


if __name__ == "__main__":
    if sys.argv[1:2] == ["scaling"]:
        scaling(*map(int, sys.argv[2:]))
    elif sys.argv[1:2] == ["measure"]:
        measure(*map(int, sys.argv[2:]))
    else:
        main(*map(int, sys.argv[1:]))
