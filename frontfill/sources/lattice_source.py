"""A Python data source of lattice sites, and sinks for points."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from frontfill.functions.lattice import BITS, SIDE
from frontfill.operators.tree import point_key


class _Rows(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class LatticeSource(DataSource):
    """``spark.read.format("lattice").option("step", n).load()``: sites ``x0, x1`` of a square lattice."""

    @classmethod
    def name(cls) -> str:
        return "lattice"

    def schema(self) -> str:
        return "x0 bigint, x1 bigint"

    def reader(self, schema):
        return _Reader(int(self.options.get("step", "1048576")), int(self.options.get("parts", "8")))


class _Reader(DataSourceReader):
    def __init__(self, step: int, parts: int):
        self.step, self.parts = step, parts

    def partitions(self):
        n = -(-SIDE // self.step)
        per = -(-n // self.parts)
        return [_Rows(lo, min(n, lo + per)) for lo in range(0, n, per)]

    def read(self, partition):
        import pyarrow as pa

        n = -(-SIDE // self.step)
        xs = [i * self.step for i in range(partition.lo, partition.hi) for _ in range(n)]
        ys = [j * self.step for _ in range(partition.lo, partition.hi) for j in range(n)]
        yield pa.RecordBatch.from_pydict({"x0": pa.array(xs, pa.int64()), "x1": pa.array(ys, pa.int64())})


def write_points(points: DataFrame, path: str, names: list[str], prefix_level: int = 4, mode: str = "overwrite") -> None:
    """Points by key prefix: a folder a coarse cell, rows in key order inside, so cell ranges prune folders and row groups."""
    d = len(names)
    keyed = points.withColumn("code", point_key(names, BITS // d if d > 2 else 12)).withColumn("code_prefix", point_key(names, prefix_level))
    keyed.repartitionByRange(F.col("code")).sortWithinPartitions("code").write.mode(mode).partitionBy("code_prefix").parquet(path)


def read_points(spark, path: str, prefixes: list[int] | None = None) -> DataFrame:
    """Stored points, of some coarse cells only if given (folder pruning)."""
    df = spark.read.parquet(path)
    return df if prefixes is None else df.where(F.col("code_prefix").isin(prefixes))


def read_polygon(spark, path: str) -> tuple[tuple[int, int], ...]:
    """Corners of a polygon from a CSV file with columns ``ord, x, y``; a region's outline, not data."""
    rows = spark.read.option("header", True).schema("ord int, x long, y long").csv(path).orderBy("ord").collect()
    return tuple((r["x"], r["y"]) for r in rows)
