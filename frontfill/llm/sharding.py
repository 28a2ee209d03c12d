"""Shards by a consistent-hash ring with virtual nodes and bounded loads (operator 4).

Every shard owns ``virtual`` points of a ring of ``slots`` equal slots.  A row hashes to a
place on the ring and belongs to the owner of the next virtual node clockwise; when that shard is
full the row continues clockwise to the next shard with room.  The bound on a shard's load is
the exact share (rows over shards, up or down), so shards end at most one row apart: the
law is ``rows``.  Only overflowing rows leave the owner that plain consistent hashing names.

DataFrame operations only.  Rows are ranked inside their slot; one count a slot, a number
fixed by the parameter and not by the data, goes to the driver, which walks the ring and returns
for each slot the runs of ranks that each shard takes.  Rows find their run by a
broadcast join of that bounded table.  No step depends on the order of arrival, so the
result is the same for every partitioning.

Defined results: null text counts as no bytes; equal texts are ordinary separate rows; rows that
repeat as a whole take neighbouring places; null identifiers hash like a value; other columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from frontfill.llm.common import safe_text

SHARDS, VIRTUAL, SLOTS = 16, 64, 16_384


def ring(shards: int, virtual: int, slots: int) -> list[int]:
    """Owner of each slot: that of the first virtual node at or after it."""
    nodes = sorted((int.from_bytes(hashlib.sha256(f"{s}/{v}".encode()).digest()[:8], "big") % slots, s) for s in range(shards) for v in range(virtual))
    places = [p for p, _ in nodes]
    return [nodes[bisect_left(places, k) % len(nodes)][1] for k in range(slots)]


def clockwise(owner: list[int], shards: int) -> list[list[int]]:
    """For each slot the shards in the order in which their next virtual nodes come clockwise."""
    n = len(owner)
    order: list[int] = list(dict.fromkeys(owner[k] for k in range(n)))
    order += [s for s in range(shards) if s not in order]
    out: list[list[int]] = [[]] * n
    for k in range(n - 1, -1, -1):
        order = [owner[k], *(s for s in order if s != owner[k])]
        out[k] = order
    # the walk above starts at slot 0's order from a full turn, so the last slots see what follows them
    return out


def plan(counts: dict[int, int], shards: int = SHARDS, virtual: int = VIRTUAL, slots: int = SLOTS) -> list[tuple[int, int, int, int, int]]:
    """``slot, from, to, shard, base``: rows of rank ``from..to-1`` of a slot take places ``base..`` of a shard.

    First each slot's rows fill their owner while it has room; then, walking the ring, what is left moves on
    to the next shard with room.  Larger shares go to the first shards, by number.
    """
    total = sum(counts.values())
    room = [total // shards + (s < total % shards) for s in range(shards)]
    owner = ring(shards, virtual, slots)
    order = clockwise(owner, shards)
    used = [0] * shards
    runs, rest = [], []
    for k in sorted(counts):
        s, n = owner[k], counts[k]
        take = min(n, room[s] - used[s])
        if take:
            runs.append((k, 0, take, s, used[s]))
            used[s] += take
        if take < n:
            rest.append((k, take, n))
    for k, at, n in rest:
        for s in order[k]:
            take = min(n - at, room[s] - used[s])
            if take:
                runs.append((k, at, at + take, s, used[s]))
                used[s] += take
                at += take
            if at == n:
                break
    return runs


def shard_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shards: int = SHARDS, virtual: int = VIRTUAL, slots: int = SLOTS) -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard`` for every row."""
    text = safe_text(text_col)
    rows = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    place = F.xxhash64(F.lit("ring"), F.col("doc_id"), F.col("text_crc32"))
    rows = rows.withColumn("place", place).withColumn("cell", F.pmod(F.shiftrightunsigned("place", 16), F.lit(slots)).cast("int"))
    counts = {r["cell"]: r["n"] for r in rows.groupBy("cell").agg(F.count("*").alias("n")).collect()}
    runs = docs.sparkSession.createDataFrame(plan(counts, shards, virtual, slots), "cell int, lo long, hi long, shard int, base long")
    ranked = rows.withColumn("rank", F.row_number().over(Window.partitionBy("cell").orderBy("place", "doc_id", "text_crc32")) - 1)
    # a row for each slot and shard that shares it: bounded by slots + shards * shards, whatever the data
    got = ranked.join(F.broadcast(runs.withColumnRenamed("cell", "c")), (F.col("cell") == F.col("c")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    return got.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", (F.col("base") + F.col("rank") - F.col("lo")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
