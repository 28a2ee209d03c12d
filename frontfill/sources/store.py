"""Shared storage between the jobs of an iterative plan."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame


def stored(df: DataFrame) -> DataFrame:
    """``df`` written once to the session's shared checkpoint folder: a cut of the lineage that outlives executors."""
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="frontfill-ckpt-"))
    return df.checkpoint(eager=True)
