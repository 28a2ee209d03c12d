"""Quality rules with risk-controlled cutoffs (operator 1).

Fixed base rules come first: too few words, or too large a share of words in repeated three-word windows.
Beyond them a document is rejected where a badness score passes its stratum's cutoff, and the cutoffs are
chosen on labelled documents so that they reject few good ones *with a guarantee*:

* the strata are the values of one column (language by default);
* for each stratum and score, cutoffs of a fixed grid are tried from the mildest on.  A cutoff is certified when the
  exact binomial test rejects "more than ``alpha / scores`` of good documents fall beyond it" at level
  ``delta / (strata * scores)`` -- Bonferroni over strata and scores; inside a grid the fixed order of testing, which
  ends at the first failure, needs no further correction;
* the strictest certified cutoff holds.  A stratum with too few labels certifies none and rejects nothing.

With probability ``1 - delta`` no stratum loses more than ``alpha`` of its good documents to the cutoffs.

All documents are measured once, array-at-a-time, without a shuffle; what calibration gathers is one count for each
(stratum, score, grid step), summed map-side.  The cutoff table has a row a stratum; strata that have no labels need none.

Defined results: null and empty texts have no words and fail the base rules; a null stratum is a stratum of its own;
repeated labels of one document count once by the smallest label (a doubtful good one is not good); repeated rows are
separate documents; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm.common import checkpointed
from frontfill.llm.wordscan import IS_LEAD, IS_WORD, cover, exact_ngrams, intern, lines, pair_ids, pieces, within, words

MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
ALPHA, DELTA = 0.05, 0.05
SYMBOLS = b"#*$%&|<>"
_IS_SYMBOL = np.zeros(256, dtype=bool)
_IS_SYMBOL[list(SYMBOLS)] = True
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: per mille of the score's base, mildest cutoff first
GRID = (800, 700, 600, 500, 450, 400, 350, 300, 250, 200, 175, 150, 125, 100, 80, 60, 50, 40, 30, 20, 10)
#: score: per mille of what is bad
SCORES = {
    "symbols": "1000 * n_symbols / greatest(word_chars, 1)",
    "dup_lines": "1000 * n_dup_lines / greatest(n_words, 1)",
    "repeats": "1000 * n_repeat_words / greatest(n_words, 1)",
    "long_words": "10 * word_chars / greatest(n_words, 1)",
}


def measure(column) -> tuple[np.ndarray, ...]:
    """The five base counts of each text of a string column."""
    out = []
    for p in pieces(column):
        n = p.hi - p.lo
        lead = np.concatenate([[0], np.cumsum(IS_LEAD[p.buf] & IS_WORD[p.buf])])
        sym = np.concatenate([[0], np.cumsum(_IS_SYMBOL[p.buf])])
        w = words(p)
        n_words = np.bincount(w.doc, minlength=n)
        # repeated three-word windows inside a document, told apart by the words themselves
        g = np.flatnonzero(within(w.doc, 3))
        key = pair_ids(exact_ngrams(intern(p.buf, w), 3)[g], w.doc[g])
        covered = cover(g[np.bincount(key)[key] > 1], len(w.doc), 3)
        n_repeat = np.bincount(w.doc[covered], minlength=n)
        # lines that have a word and equal an earlier line of the document
        ln = lines(p)
        has = np.searchsorted(w.starts, ln.ends) > np.searchsorted(w.starts, ln.starts)
        key = pair_ids(intern(p.buf, ln), ln.doc)[has]
        _, at = np.unique(key, return_index=True)
        first = np.zeros(len(key), dtype=bool)
        first[at] = True
        n_dup = np.bincount(ln.doc[has][~first], minlength=n)
        out.append((n_words, lead[p.bounds[1:]] - lead[p.bounds[:-1]], sym[p.bounds[1:]] - sym[p.bounds[:-1]], n_dup, n_repeat))
    return tuple(np.concatenate(x).astype(np.int64) for x in zip(*out, strict=True)) if out else tuple(np.zeros(0, np.int64) for _ in MEASURES)


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str | None = "lang") -> DataFrame:
    """``doc_id, stratum`` and the base counts, one row a document."""
    stratum = F.col(stratum_col).cast("string") if stratum_col else F.lit("all")

    def scan(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array(x, pa.int64()) for x in measure(b.column(2)))], ["doc_id", "stratum", *MEASURES])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), stratum.alias("stratum"), F.col(text_col).alias("text"))
    return rows.mapInArrow(scan, "doc_id long, stratum string, " + ", ".join(f"{m} long" for m in MEASURES))


def binomial_cdf(k: int, n: int, p: float) -> float:
    """P(X <= k) for X ~ Bin(n, p), by the continued fraction of the incomplete beta function."""
    if k >= n:
        return 1.0
    if k < 0:
        return 0.0
    a, b, x = float(n - k), float(k + 1), 1.0 - p
    if x > (a + 1) / (a + b + 2):
        return 1.0 - _beta(b, a, 1.0 - x)
    return _beta(a, b, x)


def _beta(a: float, b: float, x: float) -> float:
    if x <= 0.0:
        return 0.0
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    tiny, c, d = 1e-300, 1.0, 1.0 - (a + b) * x / (a + 1)
    d = 1.0 / (d if abs(d) > tiny else tiny)
    f = d
    for m in range(1, 10_000):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1.0 + num * d
            d = 1.0 / (d if abs(d) > tiny else tiny)
            c = 1.0 + num / c
            c = c if abs(c) > tiny else tiny
            f *= c * d
        if abs(c * d - 1.0) < 1e-13:
            break
    return front * f


def upper_bound(k: int, n: int, level: float) -> float:
    """The exact (Clopper-Pearson) upper confidence bound of a rate after ``k`` of ``n``."""
    if k >= n:
        return 1.0
    lo, hi = k / n, 1.0
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if binomial_cdf(k, n, mid) > level else (lo, mid)
    return hi


def certified(beyond: list[int], n: int, alpha: float, level: float) -> int | None:
    """Index of the strictest cutoff of the grid that passes, with all milder ones."""
    best = None
    for i, k in enumerate(beyond):
        if binomial_cdf(k, n, alpha) > level:
            break
        best = i
    return best


def calibrate(measures: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA, id_col: str = "doc_id", label_col: str = "quality") -> DataFrame:
    """``stratum`` and one cutoff column a score (null: none certified), for strata with labels."""
    good = labels.where(f"{label_col} is not null").groupBy(F.col(id_col).cast("long").alias("doc_id")).agg(F.min(label_col).alias("q")).where("q = 1").select("doc_id")
    passed = measures.where(~base_failed()).join(good, "doc_id", "left_semi")
    counts = passed.groupBy("stratum").agg(F.count("*").alias("n"), *(F.sum((F.expr(e) > F.lit(c)).cast("long")).alias(f"{s}_{c}") for s, e in SCORES.items() for c in GRID))
    # a row a stratum; one number of them to the driver
    counts = checkpointed(counts)
    strata = counts.count()
    each = alpha / len(SCORES)

    def choose(batches):
        for b in batches:
            rows = b.to_pylist()
            out = {"stratum": pa.array([r["stratum"] for r in rows], pa.string())}
            for s in SCORES:
                at = [certified([r[f"{s}_{c}"] for c in GRID], r["n"], each, delta / (strata * len(SCORES))) for r in rows]
                out[f"cut_{s}"] = pa.array([None if i is None else GRID[i] for i in at], pa.int64())
            yield pa.RecordBatch.from_pydict(out)

    return counts.mapInArrow(choose, "stratum string, " + ", ".join(f"cut_{s} long" for s in SCORES))


def base_failed():
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))


def judge(docs: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA, id_col: str = "doc_id", text_col: str = "text", stratum_col: str | None = "lang", max_strata: int = 10_000) -> DataFrame:
    """All documents with their counts, ``base_failed`` and ``kept``."""
    seen = checkpointed(measured(docs, id_col, text_col, stratum_col))
    cuts = checkpointed(calibrate(seen, labels, alpha, delta))
    cuts = cuts.withColumnRenamed("stratum", "at")
    # one row a stratum: broadcast behind a check of their number, else a join that AQE may split
    if cuts.limit(max_strata + 1).count() <= max_strata:
        cuts = F.broadcast(cuts)
    out = seen.join(cuts, F.col("stratum").eqNullSafe(F.col("at")), "left")
    rejected = F.lit(False)
    for s, e in SCORES.items():
        rejected = rejected | F.coalesce(F.expr(e) > F.col(f"cut_{s}"), F.lit(False))
    return out.select("doc_id", *MEASURES, base_failed().alias("base_failed"), (~base_failed() & ~rejected).alias("kept"), "stratum", *(f"cut_{s}" for s in SCORES))
