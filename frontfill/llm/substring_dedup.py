"""Removal of word passages that occur more than once in the corpus (operator 5).

Level-wise doubling: windows of a short length are counted over the whole corpus;
only positions whose short window is repeated can start, or end, a repeated window
of twice that length, so each next level looks at survivors alone, up to the full
length.  Nothing is sampled or capped.

Physical plan.  Documents are dealt once to *chunks* by a hash of the row; the four
passes over the text re-use that one exchange.  At each level a chunk sends each
*bucket* of the fingerprint space the sorted distinct fingerprints of its windows
(32 bits beside the bucket number, 64 at the last level) with a mark for those met
twice inside the chunk.  A bucket answers with one bit a fingerprint.  So a passage
that a third of all rows share costs one entry a chunk, a level moves 4 bytes a
distinct window, and no row for a window, a pair or an occurrence ever exists.

Defined results: null and empty texts have no words; rows that repeat as a whole
count as separate documents, so their windows are repeated; extra columns pass
through untouched, but columns of the names ``n_words`` and ``n_removed`` give way to the counts; an empty table gives an empty result.  Fingerprints that collide
at the first levels only cost a survivor; the last level holds 64 bits, of windows
whose parts were repeated too.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from frontfill.llm.common import text_bytes
from frontfill.llm.wordscan import U64, Piece, cover, ladder, ngrams, pieces, run_hashes, widen, within, words

MIN_CHUNK, MAX_CHUNK = 8 << 20, 128 << 20
SEND = "chunk int, level int, bucket int, payload binary"


def _groups(owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each run of equal values."""
    at = np.flatnonzero(np.diff(owner, prepend=-1))
    return at, np.append(at[1:], len(owner))[: len(at)]


class _Windows:
    """Fingerprints of a chunk's windows, and what the corpus has said of them, level by level."""

    def __init__(self, texts: pa.ChunkedArray, levels: list[int], buckets: int):
        self.parts: list[tuple[Piece, object]] = []
        hashes, docs, base = [], [], 0
        for p in pieces(texts):
            w = words(p)
            self.parts.append((p, w))
            hashes.append(run_hashes(p.buf, w))
            docs.append(w.doc + p.lo)
        self.wh = np.concatenate(hashes) if hashes else np.zeros(0, U64)
        self.doc = np.concatenate(docs) if docs else np.zeros(0, np.int64)
        self.levels, self.buckets = levels, buckets
        n = levels[0]
        self.h = ngrams(self.wh, n)
        self.alive = within(self.doc, n)

    def grow(self, level: int) -> None:
        """Windows of the next length whose both halves have survived."""
        have, want = self.levels[level - 1], self.levels[level]
        shift = want - have
        n = max(0, len(self.alive) - shift)
        self.alive = self.alive[:n] & self.alive[shift:][:n] & within(self.doc, want)
        self.h = widen(self.h, have, want)

    def distinct(self, level: int):
        """(bucket of each, value of each, met twice here, slot of each live window), sorted by bucket and value."""
        live = self.h[self.alive]
        last = level == len(self.levels) - 1
        bucket = (live >> U64(32)) % U64(self.buckets)
        key = live if last else (bucket << U64(32)) | (live & U64(0xFFFFFFFF))
        values, slot, count = np.unique(key, return_inverse=True, return_counts=True)
        owner = ((values >> U64(32)) % U64(self.buckets) if last else values >> U64(32)).astype(np.int64)
        if last:
            order = np.argsort(owner, kind="stable")
            back = np.empty_like(order)
            back[order] = np.arange(len(order))
            values, owner, count, slot = values[order], owner[order], count[order], back[slot]
        return owner, values, count > 1, slot

    def send(self, chunk: int, level: int) -> pa.Table:
        owner, values, twice, _ = self.distinct(level)
        width = np.uint64 if level == len(self.levels) - 1 else np.uint32
        at, end = _groups(owner)
        blobs = [np.uint32(e - s).tobytes() + np.packbits(twice[s:e]).tobytes() + values[s:e].astype(width).tobytes() for s, e in zip(at, end, strict=True)]
        k = len(at)
        return pa.table({"chunk": pa.array([chunk] * k, pa.int32()), "level": pa.array([level] * k, pa.int32()), "bucket": pa.array(owner[at], pa.int32()), "payload": pa.array(blobs, pa.binary())})

    def hear(self, level: int, answers: dict[int, bytes]) -> None:
        """Keep the windows that the buckets call repeated."""
        owner, values, _, slot = self.distinct(level)
        said = np.zeros(len(values), dtype=bool)
        at, end = _groups(owner)
        for s, e in zip(at, end, strict=True):
            said[s:e] = np.unpackbits(np.frombuffer(answers[int(owner[s])], np.uint8), count=e - s).astype(bool)
        self.alive[np.flatnonzero(self.alive)] = said[slot]


def _judge(table: pa.Table, wide: bool) -> pa.Table:
    """One bucket of one level: which values came from two chunks, or twice from one."""
    width = np.uint64 if wide else np.uint32
    sizes, twice, values = [], [], []
    for blob in table["payload"]:
        raw = blob.as_py()
        n = int(np.frombuffer(raw, np.uint32, 1)[0])
        bits = (n + 7) // 8
        sizes.append(n)
        twice.append(np.unpackbits(np.frombuffer(raw, np.uint8, bits, 4), count=n))
        values.append(np.frombuffer(raw, width, n, 4 + bits))
    all_values = np.concatenate(values)
    mark = np.concatenate(twice).astype(bool)
    _, slot, count = np.unique(all_values, return_inverse=True, return_counts=True)
    marked = np.zeros(len(count), dtype=bool)
    marked[slot[mark]] = True
    repeated = ((count > 1) | marked)[slot]
    out, at = [], 0
    for n in sizes:
        out.append(np.packbits(repeated[at : at + n]).tobytes())
        at += n
    return pa.table({"chunk": table["chunk"], "level": table["level"], "bucket": table["bucket"], "payload": pa.array(out, pa.binary())})


def _replay(texts: pa.ChunkedArray, heard: pa.Table, levels: list[int], buckets: int, upto: int) -> _Windows:
    said: dict[int, dict[int, bytes]] = {}
    for lv, b, blob in zip(heard["level"].to_pylist(), heard["bucket"].to_pylist(), heard["payload"], strict=True):
        said.setdefault(lv, {})[b] = blob.as_py()
    w = _Windows(texts, levels, buckets)
    for level in range(upto):
        w.hear(level, said.get(level, {}))
        w.alive = w.alive.copy()
        if level + 1 < len(levels):
            w.grow(level + 1)
    return w


def kept_texts(piece: Piece, runs, gone: np.ndarray, layout: str) -> list[str]:
    """The text of each document without the words marked gone.

    ``spaces`` joins kept words by one space; ``original`` cuts out the bytes from the first
    removed word of a run to the next kept word, so the rest keeps its white space.
    """
    raw = piece.buf.tobytes()
    first = np.searchsorted(runs.doc, np.arange(piece.hi - piece.lo + 1))
    out = []
    for d in range(piece.hi - piece.lo):
        lo, hi = int(first[d]), int(first[d + 1])
        b0, b1 = int(piece.bounds[d]), int(piece.bounds[d + 1])
        dead = gone[lo:hi]
        if layout == "spaces":
            if not dead.any():
                out.append(b" ".join(raw[b0:b1].split()).decode())
                continue
            keep = np.flatnonzero(~dead) + lo
            out.append(b" ".join([raw[s:e] for s, e in zip(runs.starts[keep].tolist(), runs.ends[keep].tolist(), strict=True)]).decode())
            continue
        if not dead.any():
            out.append(raw[b0:b1].decode())
            continue
        edge = np.diff(dead.astype(np.int8), prepend=0, append=0)
        cut, at = [], b0
        for s, e in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
            cut.append(raw[at : int(runs.starts[lo + s])])
            at = int(runs.starts[lo + e]) if lo + e < hi else b1
        cut.append(raw[at:b1])
        out.append(b"".join(cut).decode())
    return out


def remove_repeated(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    window: int = 35,
    base: int | None = None,
    layout: str = "original",
    chunk_bytes: int | None = None,
) -> DataFrame:
    """All input rows and columns, the text replaced by what is left, plus ``n_words`` and ``n_removed``.

    A word goes when a window of ``window`` consecutive words of its document covers it and the same
    words start anywhere else in the corpus, its own document included; windows are judged on the input.
    ``base`` is the first window length (a quarter of ``window`` by default).
    """
    docs = docs.drop("n_words", "n_removed")
    home_col = "chunk"
    while home_col in (c.lower() for c in docs.columns):
        home_col = "_" + home_col
    levels = ladder(window, base or max(1, (window + 3) // 4))
    total = text_bytes(docs, text_col)
    size = chunk_bytes or int(min(MAX_CHUNK, max(MIN_CHUNK, total / 2000)))
    chunks = max(1, -(-total // size))
    buckets = max(1, -(-total // (2 * size)))
    home = docs.withColumn(home_col, F.pmod(F.xxhash64(F.col(id_col), F.col(text_col)), F.lit(chunks)).cast("int"))
    names = docs.columns
    schema = T.StructType([*docs.schema.fields, T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType())])
    last = len(levels) - 1

    def sender(level: int):
        def with_answers(key, left, right):
            w = _replay(left[text_col], right, levels, buckets, level)
            return w.send(key[0].as_py(), level)

        def first(key, table):
            return _Windows(table[text_col], levels, buckets).send(key[0].as_py(), 0)

        return with_answers if level else first

    def judge(wide: bool):
        return lambda table: _judge(table, wide)

    def finish(key, left, right):
        left = left.combine_chunks()
        w = _replay(left[text_col], right, levels, buckets, last + 1)
        gone = cover(np.flatnonzero(w.alive), len(w.wh), window)
        texts, at = [], 0
        for p, runs in w.parts:
            texts += kept_texts(p, runs, gone[at : at + len(runs.doc)], layout)
            at += len(runs.doc)
        n_words = np.bincount(w.doc, minlength=left.num_rows)
        n_gone = np.bincount(w.doc[gone], minlength=left.num_rows)
        mask = left[text_col].is_null().combine_chunks() if left.num_rows else None
        cols = {c: left[c] for c in names}
        new = pa.array(texts, left.schema.field(text_col).type)
        cols[text_col] = pa.compute.if_else(mask, pa.scalar(None, new.type), new) if left.num_rows else new
        cols["n_words"] = pa.array(n_words, pa.int64())
        cols["n_removed"] = pa.array(n_gone, pa.int64())
        return pa.table(cols)

    heard = None
    for level in range(len(levels)):
        by_chunk = home.groupBy(home_col)
        if heard is None:
            sent = by_chunk.applyInArrow(sender(0), SEND)
        else:
            sent = by_chunk.cogroup(heard.groupBy("chunk")).applyInArrow(sender(level), SEND)
        answer = sent.groupBy("bucket").applyInArrow(judge(level == last), SEND)
        heard = answer if heard is None else heard.unionByName(answer)
    return home.groupBy(home_col).cogroup(heard.groupBy("chunk")).applyInArrow(finish, schema)
