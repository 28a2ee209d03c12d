"""Thinning and counting rows as they arrive."""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.operators.rows import _div, _offsets, thin
from frontfill.functions.lattice import squared


def thin_stream(stream: DataFrame, names: list[str], h: int, path: str, checkpoint: str, schema_cols: tuple[str, ...] = ("id",), available_now: bool = True):
    """Start a query that keeps an append-only Parquet set with the spacing ``h``.

    Each micro-batch first loses the rows near accepted ones -- read by the coarse cells that the batch touches, so old files are pruned -- and
    the rest is thinned exactly.  A batch that is run again rewrites its own folder, so recovery adds nothing twice.
    """
    coarse = 64 * h

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch = batch.select(*schema_cols, *names).withColumn("zone", _div(F.col(names[0]), coarse))
        fs = spark._jvm.org.apache.hadoop.fs.Path(path).getFileSystem(spark._jsc.hadoopConfiguration())
        root = spark._jvm.org.apache.hadoop.fs.Path(path)
        seen = [s.getPath().getName() for s in fs.listStatus(root)] if fs.exists(root) else []
        old = [f"{path}/{s}" for s in seen if s.startswith("batch=") and int(s.split("=")[1]) < number]
        if old:
            zones = [r["zone"] for r in batch.select("zone").distinct().collect()]  # a row a coarse zone of one axis
            near_zones = sorted({z + o for z in zones for o in (-1, 0, 1)})
            kept = spark.read.option("basePath", path).parquet(*old).where(F.col("zone").isin(near_zones))
            side = [f"k_{n}" for n in names]
            wide = kept.select(*(F.col(n).alias(f"k_{n}") for n in names)).select(*side, F.explode(_offsets(len(names))).alias("o"))
            wide = wide.withColumns({f"g{i}": _div(F.col(f"k_{n}"), h) + F.col("o")[i] for i, n in enumerate(names)})
            here = batch.withColumns({f"b{i}": _div(F.col(n), h) for i, n in enumerate(names)})
            cond = reduce(and_, (F.col(f"b{i}") == F.col(f"g{i}") for i in range(len(names))))
            near = squared([F.col(n) for n in names], [F.col(f"k_{n}") for n in names]) < F.lit(h * h)
            batch = here.join(wide, cond & near, "left_anti").drop(*(f"b{i}" for i in range(len(names))))
        out = thin(batch, names, h).withColumn("zone", _div(F.col(names[0]), coarse))
        out.repartition("zone").write.mode("overwrite").partitionBy("zone").parquet(f"{path}/batch={number}")

    writer = stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def rate_windows(events: DataFrame, ts: str = "ts", late: str = "1 hour", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Rows by tumbling or sliding window, behind a watermark on streams."""
    src = events.withWatermark(ts, late) if events.isStreaming else events
    win = F.window(ts, width, slide) if slide else F.window(ts, width)
    return src.groupBy(win.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def late_counts(stream: DataFrame, path: str, checkpoint: str, ts: str = "ts", late: str = "1 hour"):
    """Start a query that counts each micro-batch's rows and, of these, the late ones: ``batch, n, late, latest`` rows under ``path``.

    A row is late when it is older by more than ``late`` than the newest row of the batches before its own.  A batch leaves one row, and the next one
    reads the marks of those before it; a batch that is run again rewrites its own, so recovery counts nothing twice.
    """

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        root = spark._jvm.org.apache.hadoop.fs.Path(path)
        fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
        seen = [s.getPath().getName() for s in fs.listStatus(root)] if fs.exists(root) else []
        old = [f"{path}/{s}" for s in seen if s.startswith("mark=") and int(s.split("=")[1]) < number]
        mark = spark.read.parquet(*old).agg(F.max("latest")).first()[0] if old else None  # one value
        behind = F.col(ts) < F.lit(mark) - F.expr(f"INTERVAL {late}") if mark is not None else F.lit(False)
        row = batch.agg(F.count("*").alias("n"), F.coalesce(F.sum(behind.cast("long")), F.lit(0)).cast("long").alias("late"), F.max(ts).alias("latest"))
        row.select(F.lit(number).cast("long").alias("batch"), "n", "late", "latest").coalesce(1).write.mode("overwrite").parquet(f"{path}/mark={number}")

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def with_static(stream: DataFrame, static: DataFrame, on: str, key: str, how: str = "inner") -> DataFrame:
    """A stream's rows with those of a table; which side is sent to all tasks is left to the optimiser's size check, batch by batch."""
    return stream.join(static, stream[on] == static[key], how)


def follow_ups(first: DataFrame, second: DataFrame, key: str, within: str, ts: str = "ts", late: str = "1 day") -> DataFrame:
    """``key, first_id, second_id``: rows of the second stream at most ``within`` after one of the first with the same key.

    Both sides (``id, key, ts``) carry a watermark, and the bound on their times lets the state drop what nothing can match any more.
    """
    a = first.select(F.col(key).alias("key"), F.col("id").alias("first_id"), F.col(ts).alias("t1"))
    b = second.select(F.col(key).alias("key2"), F.col("id").alias("second_id"), F.col(ts).alias("t2"))
    if first.isStreaming:
        a, b = a.withWatermark("t1", late), b.withWatermark("t2", late)
    met = (F.col("key") == F.col("key2")) & (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"INTERVAL {within}"))
    return a.join(b, met).select(F.col("key").alias(key), "first_id", "second_id")


def sessions(events: DataFrame, key: str, ts: str = "ts", gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Runs of a key's rows without a pause of ``gap``."""
    src = events.withWatermark(ts, late) if events.isStreaming else events
    return src.groupBy(F.col(key), F.session_window(ts, gap).alias("w")).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def first_in_cell(stream: DataFrame, names: list[str], side: int, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """One row a cell of ``side`` and watermark span: a state of one key a cell, dropped behind the watermark."""
    keyed = stream.withColumns({f"g{i}": _div(F.col(n), side) for i, n in enumerate(names)})
    if stream.isStreaming:
        return keyed.withWatermark(ts, late).dropDuplicatesWithinWatermark([f"g{i}" for i in range(len(names))])
    return keyed.dropDuplicates([f"g{i}" for i in range(len(names))])


class CellThinner:
    """Stateful thinning of one coarse cell for ``transformWithStateInPandas``: accepted points are its state.

    Rows nearer than half a spacing to the cell's border are passed on as ``deferred``, so two cells can never accept a clash; the
    deferred rows belong to the exact path of :func:`thin_stream`.
    """

    def __init__(self, names: list[str], h: int, coarse: int):
        self.names, self.h, self.coarse = names, h, coarse

    def init(self, handle) -> None:
        fields = ", ".join(f"{n} long" for n in self.names)
        self.points = handle.getListState("points", fields)

    def handleInputRows(self, key, rows, timerValues):  # noqa: N802, N803
        import numpy as np
        import pandas as pd

        kept = [tuple(p) for p in self.points.get()]
        out = []
        for frame in rows:
            frame = frame.sort_values("id")
            for r in frame.itertuples(index=False):
                x = tuple(int(getattr(r, n)) for n in self.names)
                edge = min(min(v % self.coarse, self.coarse - 1 - v % self.coarse) for v in x)
                if edge * 2 < self.h:
                    out.append((int(r.id), *x, True))
                elif not kept or (((np.array(kept) - np.array(x)) ** 2).sum(axis=1) >= self.h**2).all():
                    kept.append(x)
                    self.points.appendValue(x)
                    out.append((int(r.id), *x, False))
        yield pd.DataFrame(out, columns=["id", *self.names, "deferred"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):  # noqa: N802, N803
        return iter(())

    def handleInitialState(self, key, initialState, timerValues):  # noqa: N802, N803
        return None

    def close(self) -> None:
        return None


def thin_stateful(stream: DataFrame, names: list[str], h: int, coarse: int) -> DataFrame:
    """``id, x0.., deferred`` of a stream, thinned cell by cell with state."""
    from pyspark.sql.streaming import StatefulProcessor

    class Processor(CellThinner, StatefulProcessor):
        pass

    cells = [f"g{i}" for i in range(len(names))]
    keyed = stream.select("id", *names).withColumns({c: _div(F.col(n), coarse) for c, n in zip(cells, names, strict=True)})
    schema = "id long, " + ", ".join(f"{n} long" for n in names) + ", deferred boolean"
    return keyed.groupBy(*cells).transformWithStateInPandas(Processor(names, h, coarse), schema, "Append", "None")
