"""Small helpers shared by the text operators."""

from __future__ import annotations

import tempfile

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def checkpointed(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the session's shared checkpoint folder and read it from there.

    The folder is ``spark.checkpoint.dir``; a private one is made only where the
    session names none and runs on one machine (tests), a cluster must name one that all its machines share.
    The copy survives lost executors.
    """
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        where = spark.conf.get("spark.checkpoint.dir", None)
        if not where and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        sc.setCheckpointDir(where or tempfile.mkdtemp(prefix="frontfill-ckpt-"))
    return df.checkpoint(eager=True)


def text_bytes(docs: DataFrame, text_col: str = "text") -> int:
    """UTF-8 bytes of a text column over all rows: one narrow scan, one number to the driver."""
    row = docs.agg(F.sum(F.octet_length(F.col(text_col))).alias("b")).first()
    return int(row["b"] or 0)


def documents(spark, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def safe_text(text_col: str = "text") -> Column:
    return F.coalesce(F.col(text_col), F.lit(""))
