"""Token counts by a two-tier map-side lookup (operator 3).

Tier one is a compact table of the token lengths of frequent pre-tokens, broadcast once; its size is bounded by a parameter.  Tier two is a
cache in each worker, bounded too, that encodes whatever the table lacks.  A document's count is the sum over
its pre-tokens; nothing is shuffled but the rows of the frequency table itself, of which each task
sends its ``table_size`` best.  The table only saves time: a pre-token outside it is encoded, so the counts are the
library's whatever the table holds.  It is filled from the pre-tokens of all documents, counted map-side.

Defined results: null and empty texts have 0 bytes and 0 tokens; a special token's string inside a text is
handled by the library's default; repeated rows are separate; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm.common import checkpointed
from frontfill.llm.units import BYTE_UNITS, MAX_UNIT, Misses, plain, tokenizer

VOCABULARY = "byte_bpe_50k.json"
LIMIT = 512
TABLE_SIZE = 32_768
_cache: dict[str, Misses] = {}


def frequent_units(docs: DataFrame, text_col: str = "text", vocabulary: str = VOCABULARY, table_size: int = TABLE_SIZE) -> dict[str, int]:
    """Token length of the most frequent pre-tokens of all documents.

    Each task counts its own, with counters pruned to the largest when they grow past a bound, and sends its best; the sums are cut at
    the count that at most ``table_size`` of them reach, so that many rows come to the driver and no more.
    """

    def count(batches):
        seen: Counter = Counter()
        for b in batches:
            for t in b.column(0).to_pylist():
                if t and plain(t):
                    seen.update(BYTE_UNITS.findall(t))
                    if len(seen) > 8 * table_size:
                        seen = Counter(dict(seen.most_common(2 * table_size)))
        best = [x for x in seen.most_common(table_size) if len(x[0]) <= MAX_UNIT]
        if best:
            yield pa.RecordBatch.from_pydict({"unit": [u for u, _ in best], "n": [n for _, n in best]})

    sent = docs.select(F.col(text_col).alias("text")).mapInArrow(count, "unit string, n long")
    summed = checkpointed(sent.groupBy("unit").agg(F.sum("n").alias("n")).withColumn("grade", F.floor(8 * F.log2("n")).cast("int")))
    grades = sorted(((r["grade"], r["k"]) for r in summed.groupBy("grade").agg(F.count("*").alias("k")).collect()), reverse=True)
    room, least = table_size, None
    for grade, k in grades:
        if k > room:
            break
        room, least = room - k, grade
    else:
        grade = None
    best = summed.where(F.lit(False)) if least is None else summed.where(F.col("grade") >= least)
    # the grade that does not go in whole fills what room is left; which of its units do matters for time alone
    if grade is not None:
        best = best.unionByName(summed.where(F.col("grade") == grade).limit(room))
    units = [r["unit"] for r in best.select("unit").collect()]
    encoded = tokenizer(vocabulary).encode_batch(units, add_special_tokens=False)
    return {u: len(e) for u, e in zip(units, encoded, strict=True)}


def count_tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, limit: int = LIMIT, table_size: int = TABLE_SIZE) -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` for every row."""
    table = docs.sparkSession.sparkContext.broadcast(frequent_units(docs, text_col, vocabulary, table_size))

    def scan(batches):
        tok = tokenizer(vocabulary)
        if vocabulary not in _cache:
            _cache[vocabulary] = Misses(lambda u: len(tok.encode(u, add_special_tokens=False)))
        first, misses = table.value, _cache[vocabulary]
        for b in batches:
            sizes, counts = [], []
            for t in b.column(1).to_pylist():
                t = t or ""
                if plain(t):
                    n = 0
                    for u, k in Counter(BYTE_UNITS.findall(t)).items():
                        n += k * (first.get(u) or misses[u])
                else:
                    n = len(tok.encode(t, add_special_tokens=False))
                counts.append(n)
                sizes.append(len(t.encode()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64()), pa.array(counts, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(scan, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > F.lit(limit))
