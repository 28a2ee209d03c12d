"""Exact duplicates by a content sort, with DataFrame operations only (operator 9).

Texts are equal when their bytes are identical after white space ``[\\x20\\x09-\\x0D]`` is deleted.
The normalised text is range-partitioned by sampled splitters -- its head, a hash of the whole and a salt of
the row -- so a text that a third of all rows share is spread over several ranges; within a range an
external sort puts equal texts side by side and a sorted aggregation compares each full
text with its neighbour, keeping of a run the best row: most code points in the original
text, then the smallest identifier.  Runs of one text (at most ``SALTS``) then meet by their
SHA-256, and every row looks its run's survivor up by that digest.

Defined results: null text counts as empty, and all empty texts are one group; rows that repeat as a
whole are separate members of their group and share its verdict, unless ``row_col`` names a unique
column without nulls: it breaks ties of identifiers, so just one row of each group is kept; a null
identifier sorts after all others; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from frontfill.llm.common import safe_text, text_bytes

SALTS = 64
HEAD = 32
_SPACE = "[\\x20\\x09-\\x0D]+"


def normalised(text_col: str = "text") -> Column:
    return F.regexp_replace(safe_text(text_col), _SPACE, "")


def _ranges(docs: DataFrame, text_col: str, range_bytes: int) -> int:
    """As many ranges as the shuffle setting, or more where each would hold over ``range_bytes``."""
    set_to = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(set_to, -(-text_bytes(docs, text_col) // range_bytes))


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", range_bytes: int = 64 << 20, row_col: str | None = None) -> DataFrame:
    """``doc_id, keep_id, group_size, kept, text_sha256`` for every row, and its ``row`` when ``row_col`` is given."""
    own = [F.col(row_col).alias("row")] if row_col else []
    key = ["row"] if row_col else []
    rows = docs.select(F.col(id_col).alias("doc_id"), normalised(text_col).alias("norm"), F.length(safe_text(text_col)).alias("size"), *own)
    # nulls last among equals
    best = F.struct((-F.col("size")).alias("less"), F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), *key)
    salted = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "size", *key), F.lit(SALTS)))
    # splitters are short: the head of the bytes, then a hash of all of them and the salt, so sampled keys stay small however long texts are
    salted = salted.withColumns({"head": F.substring("norm", 1, HEAD), "mark": F.xxhash64("norm")})
    sorted_runs = salted.repartitionByRange(_ranges(docs, text_col, range_bytes), "head", "mark", "salt").sortWithinPartitions("head", "mark", "salt", "norm")
    runs = sorted_runs.groupBy("head", "mark", "salt", "norm").agg(F.min(best).alias("best"), F.count("*").alias("n"))
    groups = runs.select(F.sha2("norm", 256).alias("text_sha256"), "best", "n").groupBy("text_sha256").agg(F.min("best").alias("best"), F.sum("n").alias("group_size"))
    each = rows.select("doc_id", *key, F.sha2("norm", 256).alias("text_sha256"))
    return each.join(groups, "text_sha256").select(
        "doc_id",
        F.col("best.id").alias("keep_id"),
        F.col("group_size").cast("long").alias("group_size"),
        (F.col("row") == F.col("best.row") if row_col else F.col("doc_id").eqNullSafe(F.col("best.id"))).alias("kept"),
        "text_sha256",
        *key,
    )
