"""Registered queries of the text operators and their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm import chat_format, exact_dedup, language_id, minhash_dedup, packing, pieces_codec, quality_rules, sharding, substring_dedup, token_counts
from frontfill.llm.common import documents, safe_text
from frontfill.llm.queries_sql import ORACLES  # noqa: F401


def op1_quality_rules(spark, sf_dir: str) -> DataFrame:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    out = quality_rules.judge(documents(spark, sf_dir), labels)
    return out.select("doc_id", *quality_rules.MEASURES, "base_failed", "kept")


def op2_minhash_dedup(spark, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(documents(spark, sf_dir), shingle=4, threshold=0.8)


def op3_token_counts(spark, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(documents(spark, sf_dir))


def op4_sharding(spark, sf_dir: str) -> DataFrame:
    return sharding.shard_rows(documents(spark, sf_dir))


def op5_substring_dedup(spark, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    out = substring_dedup.remove_repeated(docs, window=35, layout="spaces")
    return out.select("doc_id", "n_words", "n_removed", F.sha2(safe_text(), 256).alias("kept_sha256"))


def op6_chat_format(spark, sf_dir: str) -> DataFrame:
    say = "</s>[INST] ok [/INST]"
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    extra = spark.createDataFrame([(-7, 0, "user", say), (-7, 1, "assistant", say)], turns.schema)
    back = chat_format.read_back(chat_format.windows(turns.unionByName(extra)))
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        "n_turns",
        F.sha2(told, 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        "formatted_chars",
    )


def op7_packing(spark, sf_dir: str) -> DataFrame:
    return packing.pack_documents(documents(spark, sf_dir))


def op8_language_id(spark, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    samples = language_id.training_samples(docs, ~language_id.held_out())
    out = language_id.identify(docs.select("doc_id", "text"), samples)
    return out.select("doc_id", language_id.held_out().alias("held_out"), "lang_pred", "score")


def op9_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(documents(spark, sf_dir))


def op10_sentencepiece(spark, sf_dir: str) -> DataFrame:
    return pieces_codec.encode_documents(documents(spark, sf_dir), with_ids=False)


QUERIES = {
    "op1_quality_rules": op1_quality_rules,
    "op2_minhash_dedup": op2_minhash_dedup,
    "op3_token_counts": op3_token_counts,
    "op4_sharding": op4_sharding,
    "op5_substring_dedup": op5_substring_dedup,
    "op6_chat_format": op6_chat_format,
    "op7_packing": op7_packing,
    "op8_language_id": op8_language_id,
    "op9_exact_dedup": op9_exact_dedup,
    "op10_sentencepiece": op10_sentencepiece,
}
