"""The corpus pipeline: language, exact copies, near copies, repeated passages, packing.

Each stage takes what the one before it kept, as a table with the columns of ``documents``, and applies one operator
with production parameters; :func:`run` writes nothing itself but chains the stages through the shared checkpoint folder.

From the first stage to the last that rejects copies a unique ``row`` number goes with each document, and verdicts are joined
by it: identifiers may repeat or be null.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm import exact_dedup, language_id, minhash_dedup, packing, substring_dedup
from frontfill.llm.common import checkpointed

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
ROW = "row"


def numbered(docs: DataFrame) -> DataFrame:
    """The documents with their row number; one that is not there yet is stored, because a second run might count otherwise."""
    if ROW in docs.columns:
        return docs.select(*COLUMNS, ROW)
    return checkpointed(docs.select(*COLUMNS).withColumn(ROW, F.monotonically_increasing_id()))


def language_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language, with the predicted one in ``lang``: those without a letter are rejected."""
    samples = language_id.training_samples(docs, ~language_id.held_out())
    tagged = language_id.identify(docs.select(*COLUMNS), samples, out=("pred", "pred_score"))
    said = tagged.where("pred <> 'und'").withColumn("lang", F.col("pred"))
    # numbered here, where the row is stored once and for all
    return said.select(*COLUMNS, F.monotonically_increasing_id().alias(ROW))


def _only(docs: DataFrame, stay: DataFrame) -> DataFrame:
    """The documents whose row number is among those that stay."""
    return docs.join(stay.select(ROW), ROW, "left_semi")


def exact_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    docs = numbered(docs)
    return _only(docs, exact_dedup.exact_duplicates(docs, row_col=ROW).where("kept")).select(*COLUMNS, ROW)


def near_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies, that with the smallest identifier: five-word shingles, similarity 0.8."""
    docs = numbered(docs)
    classes = minhash_dedup.near_duplicates(docs, id_col=ROW, shingle=5, threshold=0.8).select(F.col("doc_id").alias(ROW), "component_id")
    # a null identifier sorts after all others
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", ROW)).alias("first")
    stay = docs.select("doc_id", ROW).join(classes, ROW).groupBy("component_id").agg(first).select(F.col(f"first.{ROW}").alias(ROW))
    return _only(docs, stay).select(*COLUMNS)


def passage_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages of 50 words or more that occur elsewhere; a document of which no word is left goes."""
    cut = substring_dedup.remove_repeated(docs.select(*COLUMNS), window=50, layout="original")
    left = cut.where((F.col("n_removed") == 0) | (F.col("n_removed") < F.col("n_words")))
    return left.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.length("text")).otherwise(F.col("n_chars")).cast("long")).select(*COLUMNS)


def packing_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of all documents in sequences of 2048."""
    return packing.pack_documents(docs)


STAGES = [
    ("language_id", language_stage),
    ("exact_dedup", exact_stage),
    ("near_dedup", near_stage),
    ("substring_dedup", passage_stage),
    ("packing", packing_stage),
]

#: language prediction and token ids are beyond SQL; the stages are tested against brute force instead
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = checkpointed(docs)
    return docs
