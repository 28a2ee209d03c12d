"""Packing token pieces into fixed-length sequences (operator 7).

Each document becomes its token ids and one end id, cut into blocks of the sequence length and a remainder.  Full blocks are
sequences already.  Pieces are stored once with a number of their own and dealt to randomised groups by its hash, so neither one identifier nor
a row that occurs many times can fill a group; each group is packed on its own by first-fit decreasing:
pieces from the longest down, each into the first open sequence with room, found by descending a tournament tree that
holds the largest free space below each node.  A group holds a fixed share of bytes, so its padding does not
depend on the size of the corpus, groups run in parallel, and only piece lengths travel: ids stay where they were made
unless asked for.

Defined results: null and empty texts are the end id alone; repeated rows are packed as separate pieces; other columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm.common import checkpointed, text_bytes
from frontfill.llm.units import WORD_UNITS, Misses, plain, tokenizer, unit_ids

VOCABULARY = "word_bpe_49k.json"
LENGTH, END_ID = 2048, 1
GROUP_BYTES = 24 << 20
_cache: dict[str, Misses] = {}


def token_pieces(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, length: int = LENGTH, end_id: int = END_ID, with_ids: bool = False) -> DataFrame:
    """``doc_id, start, length, ids_crc32, doc_tokens`` (and ``ids``, little-endian 32-bit) of each piece."""
    end, step = np.uint32(end_id).tobytes(), 4 * length

    def scan(batches):
        tok = tokenizer(vocabulary)
        if vocabulary not in _cache:
            _cache[vocabulary] = Misses(unit_ids(tok))
        known = _cache[vocabulary].__getitem__
        for b in batches:
            ids = b.column(0).to_pylist()
            for lo in range(0, len(ids), 1000):
                cols: list[list] = [[], [], [], [], []]
                blobs = []
                for i, t in zip(ids[lo : lo + 1000], b.column(1).slice(lo, 1000).to_pylist(), strict=True):
                    t = t or ""
                    if plain(t):
                        raw = b"".join(map(known, WORD_UNITS.findall(t.lower()))) + end
                    else:
                        raw = np.array(tok.encode(t, add_special_tokens=False).ids, np.uint32).tobytes() + end
                    for at in range(0, len(raw), step):
                        part = raw[at : at + step]
                        for c, x in zip(cols, (i, at // 4, len(part) // 4, zlib.crc32(part), len(raw) // 4), strict=True):
                            c.append(x)
                        if with_ids:
                            blobs.append(part)
                arrays = [pa.array(c, pa.int64()) for c in cols] + ([pa.array(blobs, pa.binary())] if with_ids else [])
                yield pa.RecordBatch.from_arrays(arrays, ["doc_id", "start", "length", "ids_crc32", "doc_tokens", *["ids"] * with_ids])

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long" + ", ids binary" * with_ids
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(scan, schema)


class Tournament:
    """Largest free space of bins ``0, 1, 2, ...``; finds the first bin with room in logarithmic steps."""

    def __init__(self, bins: int, capacity: int):
        self.leaves = 1 << max(0, bins - 1).bit_length()
        self.best = [capacity] * (2 * self.leaves)

    def place(self, size: int) -> tuple[int, int]:
        """Put a size into the first bin with room: (bin, free space before)."""
        best, k, n = self.best, 1, self.leaves
        while k < n:
            k *= 2
            if best[k] < size:
                k += 1
        free = best[k]
        best[k] = free - size
        at = k - n
        k //= 2
        while k:
            a, b = best[2 * k], best[2 * k + 1]
            top = a if a > b else b
            if best[k] == top:
                break
            best[k] = top
            k //= 2
        return at, free


def first_fit_decreasing(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each size, for sizes given from the largest down."""
    bins, offsets = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
    full = int(np.searchsorted(-sizes, -capacity, side="right"))
    bins[:full] = np.arange(full)
    rest = sizes[full:].tolist()
    if rest:
        tree = Tournament(len(rest), capacity)
        got = [tree.place(s) for s in rest]
        bins[full:] = full + np.array([g[0] for g in got])
        offsets[full:] = capacity - np.array([g[1] for g in got])
    return bins, offsets


def pack(pieces: DataFrame, groups: int, length: int = LENGTH, seed: int = 7) -> DataFrame:
    """The pieces with ``sequence_id`` and ``offset``; sequences of one group follow from its number and place."""
    names = pieces.columns
    # stored, because another run of a lost task might number its rows otherwise
    numbered = checkpointed(pieces.withColumn("piece", F.monotonically_increasing_id()))
    keyed = numbered.withColumn("pack_group", F.pmod(F.xxhash64(F.lit(seed), "piece"), F.lit(groups)))

    def one(key, table):
        table = table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("start", "ascending"), ("ids_crc32", "ascending")])
        bins, offsets = first_fit_decreasing(table["length"].to_numpy(), length)
        cols = {c: table[c] for c in names}
        cols["sequence_id"] = pa.array((key[0].as_py() << 32) + bins, pa.int64())
        cols["offset"] = pa.array(offsets, pa.int64())
        return pa.table(cols)

    schema = ", ".join(f"`{n}` {t}" for n, t in pieces.dtypes) + ", sequence_id long, offset long"
    return keyed.groupBy("pack_group").applyInArrow(one, schema)


def pack_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, length: int = LENGTH, end_id: int = END_ID, with_ids: bool = False, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """Pieces of all documents, packed: ``doc_id, start, length, ids_crc32, doc_tokens, [ids,] sequence_id, offset``."""
    groups = max(1, -(-text_bytes(docs, text_col) // group_bytes))
    return pack(token_pieces(docs, id_col, text_col, vocabulary, length, end_id, with_ids), groups, length)
