"""Near-duplicate classes by bottom-k sketches from one hash function (operator 2).

Steps, each over all documents:

1. *Sketch.*  A document's shingle set is hashed once; its ``k`` smallest values are its
   sketch.  Documents of the same words fold into one representative (a partial
   aggregation on a 128-bit digest of the words, so thousands of copies are one row a task).
2. *Inverted lists of retained values.*  Two sets with Jaccard similarity ``t`` or more share
   at least ``o`` of their retained values but for a chance below 1e-8 (``k`` = 48, ``o`` = 18,
   ``t`` = 0.8), hence at least one of the ``k - o + 1`` rarest of each.  Only those are listed;
   values of one document alone fill the places of rare ones and list nothing, so common
   passages leave the lists of all documents that have text of their own.
3. *Families.*  Each list ties its members to its smallest one; the components of these ties are the families inside which
   all links must lie.  A family is tied by as many rows as its lists are long, never by pairs.
4. *Links.*  Families are dealt to units of bounded size; one over the bound is cut into blocks, and every two of its
   blocks meet in a unit.  Inside a unit the most typical documents come first.  Against one document the retained
   values' postings count overlaps, the union of the two sketches estimates the similarity of those that overlap enough,
   and the postings of the full sets, whose shingles are numbered by their words and not by a hash, verify exactly.  Documents that are already connected need no comparison, and a unit
   returns one link for each component that a document touches, so copies of one text cost their number, not its square.
5. Components over all verified links; copies inherit their representative's.

Links are decided by ``100 * |A & B| >= 100 * t * |A | B|`` on the full sets only.

Defined results: null, empty and wordless texts have no shingles, link with nothing and are
their own component; with fewer words than a shingle the whole sequence is the one shingle;
repeated rows of one ``doc_id`` are one document; null ``doc_id`` rows are left out of the
links and keep a null component; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm.common import checkpointed
from frontfill.llm.graph import components
from frontfill.llm.wordscan import LOWER, U64, exact_ngrams, intern, mix, ngrams, pieces, run_hashes, words

K, OVERLAP = 48, 18
UNIT_BYTES = 4 << 20


def shingle_sets(column, n: int):
    """The sorted distinct 64-bit shingle values of each text of a column, in order."""
    for p in pieces(column):
        w = words(p)
        wh = run_hashes(p.buf, w, lower=True)
        grams = ngrams(wh, n)
        first = np.searchsorted(w.doc, np.arange(p.hi - p.lo + 1))
        for d in range(p.hi - p.lo):
            lo, hi = int(first[d]), int(first[d + 1])
            size = hi - lo
            if size == 0:
                yield np.zeros(0, U64)
            elif size < n:
                whole = wh[lo:hi]
                h = U64(size)
                for x in whole:
                    h = mix(np.array([h ^ x], U64))[0]
                yield np.array([h], U64)
            else:
                yield np.unique(grams[lo : hi - n + 1])


def exact_sets(column, n: int) -> list[np.ndarray]:
    """The shingles of each text of a column, numbered so that equal numbers are equal words: sorted distinct numbers a text."""
    out: list[np.ndarray] = []
    for p in pieces(column, limit=1 << 62):
        w = words(p)
        ids = intern(p.buf, w, lower=True)
        grams = exact_ngrams(ids, n)
        short: dict[tuple, int] = {}
        first = np.searchsorted(w.doc, np.arange(p.hi - p.lo + 1))
        for d in range(p.hi - p.lo):
            lo, hi = int(first[d]), int(first[d + 1])
            if hi - lo >= n:
                out.append(np.unique(grams[lo : hi - n + 1]))
            elif hi > lo:
                out.append(np.array([-1 - short.setdefault(tuple(ids[lo:hi].tolist()), len(short))], np.int64))
            else:
                out.append(np.zeros(0, np.int64))
    return out


def word_digests(column) -> list[bytes | None]:
    """A 128-bit digest of the lower-cased words of each text; none without words."""
    out: list[bytes | None] = []
    for p in pieces(column):
        raw = LOWER[p.buf].tobytes()
        for s, e in zip(p.bounds[:-1].tolist(), p.bounds[1:].tolist(), strict=True):
            line = b" ".join(raw[s:e].split())
            out.append(hashlib.blake2b(line, digest_size=16).digest() if line else None)
    return out


def sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4, k: int = K) -> DataFrame:
    """``doc_id, n_shingles, digest, sketch`` for every row."""

    def scan(batches):
        for batch in batches:
            sizes, kept = [], []
            digests = word_digests(batch.column(1))
            for s in shingle_sets(batch.column(1), shingle):
                sizes.append(len(s))
                kept.append(s[:k].view(np.int64))
            flat = np.concatenate(kept) if kept else np.zeros(0, np.int64)
            offs = np.concatenate([[0], np.cumsum([len(x) for x in kept])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(offs, pa.int32()), pa.array(flat, pa.int64()))],
                ["doc_id", "n_shingles", "digest", "sketch"],
            )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(scan, "doc_id long, n_shingles long, digest binary, sketch array<long>")


def _lists(reps: DataFrame, k: int, overlap: int) -> DataFrame:
    """``v, rep``: the rarest retained values of each representative that others retain too."""
    values = reps.select("rep", F.size("sketch").alias("s"), F.explode("sketch").alias("v"))
    shared = values.groupBy("v").agg(F.count("*").alias("freq")).where("freq > 1")
    rows = values.join(shared, "v").groupBy("rep").agg(F.first("s").alias("s"), F.array_sort(F.collect_list(F.struct("freq", "v"))).alias("common"))
    need = F.greatest(F.lit(1), F.floor(F.col("s") * F.lit(overlap) / F.lit(k))).cast("int")
    # values that nobody shares come first in the order of rarity
    room = F.col("s") - need + 1 - (F.col("s") - F.size("common"))
    return rows.where(room > 0).select("rep", F.explode(F.slice("common", F.lit(1), room)).alias("x")).select("rep", F.col("x.v").alias("v"))


def _postings(values: np.ndarray, owner: np.ndarray):
    """Postings of the values that two owners have: (token of each kept entry, its owner, start of each token's owners, owners by token)."""
    _, token, count = np.unique(values, return_inverse=True, return_counts=True)
    keep = count[token] > 1
    token, owner = token[keep], owner[keep]
    _, token = np.unique(token, return_inverse=True)
    order = np.argsort(token, kind="stable")
    start = np.concatenate([[0], np.cumsum(np.bincount(token))]) if len(token) else np.zeros(1, np.int64)
    return token, owner, start, owner[order]


def _gather(tokens: np.ndarray, start: np.ndarray, owners: np.ndarray) -> np.ndarray:
    """Owners of all given tokens, with repeats."""
    lens = start[tokens + 1] - start[tokens]
    at = np.repeat(start[tokens] - (np.cumsum(lens) - lens), lens) + np.arange(int(lens.sum()))
    return owners[at]


def union_estimate(mine: np.ndarray, others: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(values of both sketches among the union's ``k`` smallest, how many those are) for one sketch and a padded matrix of others."""
    top = np.iinfo(np.uint64).max
    both = np.sort(np.concatenate([np.broadcast_to(mine, (len(others), len(mine))), others], axis=1), axis=1)
    real = both != top
    same = np.zeros_like(real)
    same[:, 1:] = both[:, 1:] == both[:, :-1]
    rank = np.cumsum(real & ~same, axis=1)
    return (same & real & (rank <= k)).sum(axis=1), np.minimum(rank[:, -1], k)


def unit_links(ids: np.ndarray, sketch: list[np.ndarray], sets: list[np.ndarray], percent: int, k: int = K, overlap: int = OVERLAP) -> list[tuple[int, int]]:
    """Links that join all documents of a unit which the similarity joins, one for each component touched.

    ``sketch`` holds the retained hash values of each document, ``sets`` its exact shingles.
    """
    n = len(sets)
    sizes = np.array([len(s) for s in sets], np.int64)
    values = np.concatenate(sets) if n else np.zeros(0, np.int64)
    token, own, start, owners = _postings(values, np.repeat(np.arange(n), sizes))
    first = np.searchsorted(own, np.arange(n + 1))
    kept = np.array([len(s) for s in sketch], np.int64)
    s_values = np.concatenate(sketch) if n else np.zeros(0, U64)
    s_token, s_own, s_start, s_owners = _postings(s_values, np.repeat(np.arange(n), kept))
    s_first = np.searchsorted(s_own, np.arange(n + 1))
    matrix = np.full((n, k), np.iinfo(np.uint64).max, U64)
    for i, s in enumerate(sketch):
        matrix[i, : kept[i]] = s
    weight = np.bincount(own, weights=np.diff(start)[token] if len(token) else None, minlength=n) / np.maximum(sizes, 1)
    label = np.arange(n)
    out = []
    for i in np.lexsort((ids, -weight)).tolist():
        mine = s_token[s_first[i] : s_first[i + 1]]
        if not len(mine):
            continue
        count = np.bincount(_gather(mine, s_start, s_owners), minlength=n)
        need = np.maximum(1, np.minimum(kept, kept[i]) * overlap // k)
        fits = (100 * np.minimum(sizes, sizes[i]) >= percent * np.maximum(sizes, sizes[i])) & (count >= need) & (label != label[i])
        near = np.flatnonzero(fits)
        if not len(near):
            continue
        hits, size = union_estimate(matrix[i, : kept[i]], matrix[near], k)
        near = near[hits * k >= overlap * size]
        if not len(near):
            continue
        both = np.bincount(_gather(token[first[i] : first[i + 1]], start, owners), minlength=n)[near]
        near = near[100 * both >= percent * (sizes[i] + sizes[near] - both)]
        if len(near):
            roots, at = np.unique(label[near], return_index=True)
            out += [(int(ids[i]), int(ids[j])) for j in near[at]]
            label[np.isin(label, roots)] = label[i]
    return out


def _units(lists: DataFrame, docs: DataFrame, id_col: str, text_col: str, unit_bytes: int) -> DataFrame:
    """``family, x, y, rep, text``: the documents of each unit; families over the bound appear once for every two of their blocks."""
    heads = lists.groupBy("v").agg(F.min("rep").alias("a"))
    ties = lists.join(heads, "v").where("a <> rep").select("a", F.col("rep").alias("b")).distinct()
    member = components(ties)
    texts = docs.select(F.col(id_col).cast("long").alias("rep"), F.col(text_col).alias("text"))
    rows = checkpointed(member.select(F.col("node").alias("rep"), F.col("root").alias("family")).join(texts, "rep"))
    bulk = rows.groupBy("family").agg(F.sum(F.octet_length("text")).alias("bytes")).select("family", F.ceil(F.col("bytes") / F.lit(unit_bytes)).cast("int").alias("blocks"), "bytes")
    bulk = checkpointed(bulk)
    rest = bulk.where("blocks <= 1").agg(F.sum("bytes").alias("b")).first()["b"] or 0
    pools = max(1, -(-int(rest) // unit_bytes))
    placed = rows.join(bulk.select("family", "blocks"), "family").select("rep", "text", "family", "blocks", F.pmod(F.xxhash64("rep"), F.greatest("blocks", F.lit(1))).cast("int").alias("block"))
    small = placed.where("blocks <= 1").select(F.lit(None).cast("long").alias("family"), F.pmod(F.xxhash64("family"), F.lit(pools)).cast("int").alias("x"), F.lit(0).alias("y"), "rep", "text")
    big = placed.where("blocks > 1").withColumn("o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("family", F.least("block", "o").alias("x"), F.greatest("block", "o").alias("y"), "rep", "text")
    return small.unionByName(big)


def near_duplicates(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    shingle: int = 5,
    threshold: float = 0.8,
    k: int = K,
    overlap: int = OVERLAP,
    unit_bytes: int = UNIT_BYTES,
) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept``: one row a document; ``kept`` marks a component's smallest id."""
    found = checkpointed(sketches(docs, id_col, text_col, shingle, k))
    real = found.where("n_shingles > 0 and doc_id is not null")
    reps = checkpointed(real.groupBy("digest").agg(F.min(F.struct("doc_id", "n_shingles", "sketch")).alias("m")).select("digest", F.col("m.doc_id").alias("rep"), F.col("m.n_shingles").alias("n_shingles"), F.col("m.sketch").alias("sketch")))
    lists = checkpointed(_lists(reps, k, overlap))
    percent = int(round(100 * threshold))

    def link(key, table):
        # one document may come in repeated rows
        ids, at = np.unique(table["rep"].to_numpy(), return_index=True)
        texts = table["text"].combine_chunks().take(pa.array(at))
        found = unit_links(ids, [s[:k] for s in shingle_sets(texts, shingle)], exact_sets(texts, shingle), percent, k, overlap)
        return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([y for _, y in found], pa.int64())})

    units = _units(lists, docs, id_col, text_col, unit_bytes)
    links = checkpointed(units.groupBy("family", "x", "y").applyInArrow(link, "a long, b long"))

    # copies of one set hang on its representative
    root = components(links)
    classes = reps.select("digest", "rep").join(root.withColumnRenamed("node", "rep"), "rep", "left").select("digest", F.coalesce("root", "rep").alias("component_id"))
    return found.select("doc_id", "n_shingles", "digest").join(classes, "digest", "left").select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
