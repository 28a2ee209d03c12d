"""The given tables, and their rows as lattice clouds ``id, grp, x0..``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.functions.lattice import axis, cents, mix


def table(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def orders(spark, sf) -> DataFrame:
    t = table(spark, sf, "orders").select("o_orderkey", "o_orderpriority", "o_orderdate", "o_totalprice")
    days = F.datediff("o_orderdate", F.to_date(F.lit("1995-01-01"))).cast("long")
    return t.select(F.col("o_orderkey").alias("id"), F.col("o_orderpriority").alias("grp"), axis(days, 0, 2500).alias("x0"), axis(cents(F.col("o_totalprice")), 0, 50_000_000).alias("x1"))


def lineitem(spark, sf) -> DataFrame:
    t = table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_returnflag", "l_quantity", "l_extendedprice", "l_discount")
    return t.select(
        (F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("id"),
        F.col("l_returnflag").alias("grp"),
        axis(F.round("l_quantity").cast("long"), 0, 51).alias("x0"),
        axis(cents(F.col("l_extendedprice")), 0, 11_000_000).alias("x1"),
        axis(cents(F.col("l_discount")), 0, 11).alias("x2"),
    )


def events_axes(t: DataFrame) -> DataFrame:
    """The cloud of an events table or stream."""
    ms = F.call_function("div", F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(1_704_067_200_000_000), F.lit(1000).cast("long"))
    return t.select(F.col("event_id").alias("id"), F.col("event_type").alias("grp"), axis(ms, 0, 2_678_400_000).alias("x0"), axis(cents(F.col("value")), 0, 100_000).alias("x1"))


def events(spark, sf) -> DataFrame:
    return events_axes(table(spark, sf, "events").select("event_id", "event_type", "ts", "value"))


def customer(spark, sf) -> DataFrame:
    t = table(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_acctbal")
    return t.select(F.col("c_custkey").alias("id"), F.col("c_nationkey").cast("string").alias("grp"), axis(cents(F.col("c_acctbal")), -100_000, 1_110_000).alias("x0"), axis(F.pmod(mix(F.col("c_custkey")), F.lit(10_007)), 0, 10_007).alias("x1"))


def supplier(spark, sf, d: int = 2) -> DataFrame:
    t = table(spark, sf, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    key = mix(F.col("s_suppkey"))
    rest = [axis(F.pmod(k, F.lit(10_007)), 0, 10_007).alias(f"x{a}") for a, k in ((1, key), (2, mix(key))) if a < d]
    return t.select(F.col("s_suppkey").alias("id"), F.col("s_nationkey").cast("string").alias("grp"), axis(cents(F.col("s_acctbal")), -100_000, 1_110_000).alias("x0"), *rest)


def part(spark, sf) -> DataFrame:
    t = table(spark, sf, "part").select("p_partkey", "p_brand", "p_size", "p_retailprice")
    return t.select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("grp"), axis(F.col("p_size").cast("long"), 0, 51).alias("x0"), axis(F.round(F.col("p_retailprice") * 10).cast("long"), 9000, 1000).alias("x1"))


def embeddings(spark, sf, d: int = 2) -> DataFrame:
    t = table(spark, sf, "embeddings")
    return t.select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("grp"), *(axis(F.floor(F.col("embedding")[a].cast("double") * (1 << 20)).cast("long"), -(1 << 20), 1 << 21).alias(f"x{a}") for a in range(d)))


def pages(spark, sf) -> DataFrame:
    t = table(spark, sf, "pages")
    return t.select(F.col("page_id").alias("id"), F.lit(None).cast("string").alias("grp"), axis(F.length("html").cast("long"), 0, 100_000).alias("x0"), axis(F.length("url").cast("long"), 0, 100).alias("x1"))


def documents(spark, sf) -> DataFrame:
    t = table(spark, sf, "documents").select("doc_id", "lang", "n_chars", "text")
    return t.select(F.col("doc_id").alias("id"), F.col("lang").alias("grp"), axis(F.col("n_chars"), 0, 200_000).alias("x0"), axis(F.size(F.split("text", " ")).cast("long"), 0, 20_001).alias("x1"))


def conversations(spark, sf) -> DataFrame:
    t = table(spark, sf, "conversations")
    return t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("role").alias("grp"), axis(F.col("turn"), 0, 8).alias("x0"), axis(F.length("text").cast("long"), 0, 4096).alias("x1"))


def benchmark(spark, sf) -> DataFrame:
    t = table(spark, sf, "benchmark")
    return t.select(F.col("item_id").alias("id"), F.lit(None).cast("string").alias("grp"), axis(F.length("text").cast("long"), 0, 512).alias("x0"))
