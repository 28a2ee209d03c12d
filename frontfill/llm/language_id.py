"""Language identification by cross-parsing against suffix automata (operator 8).

For each language a suffix automaton holds all substrings of a bounded sample of its labelled text.  A document is cut greedily into
phrases, each the longest that occurs in the sample.  A phrase costs what naming its place in the sample takes (the logarithm of
the sample's length); a symbol that the sample lacks is a phrase that costs a whole code point.  The language with the least cost in
all wins, so a sample of a few letters, against which nearly every letter is a phrase of its own, cannot win by being short.

Each language has its own alphabet: letters of its sample have symbols of their own, those beyond the commonest share a few, and
letters that the sample lacks match nothing, so scripts tell languages apart.  White space, digits and all else are three classes.

The automata are built once, by one task, and laid out as dense tables of next states with a mark for what a step closes; the tables reach
the driver and are broadcast packed alone, with a size that the sample's bound limits (two states a symbol of sample, 256 bytes a state once unpacked).  A batch of documents
advances one symbol at a time in array operations: all blocks of ``BLOCK`` symbols of all documents and all
languages at once.  The parse restarts at each block of a long text; every symbol of every text takes part.

Sample: from each of the ``SAMPLE_DOCS`` labelled texts of a language that a hash of the text puts first, a passage of ``PASSAGE`` symbols at a
hashed place, cut to the language's share of ``SAMPLE_CHARS`` in all; many short passages, so that no document's habits
weigh much.  Copies of a text count once.  A language needs ``LEAST`` symbols of sample to be predicted.

Defined results: null texts and texts without a letter are ``und`` with score 0; ties go to the language name that
sorts first; with one language the score is 1, with none all rows are ``und``; other columns pass through, but columns of the names
of the two results give way to them; repeated rows are separate; an empty table gives no rows.
"""

from __future__ import annotations

import math
import pickle
import sys
import unicodedata
import zlib
from array import array
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

SAMPLE_DOCS, SAMPLE_CHARS, PASSAGE, LEAST = 256, 1 << 18, 256, 64
BLOCK, SYMBOLS = 512, 64
SPACE, DIGIT, OTHER, UNSEEN, PAD = 0, 1, 2, 3, 63
_FIRST, SHARED = 4, 16
#: bits of a code point
LITERAL = math.log2(sys.maxunicode + 1)
PIECE_CHARS = 1 << 19


def training_samples(docs: DataFrame, fold: Column, text_col: str = "text", lang_col: str = "lang", sample_docs: int = SAMPLE_DOCS, sample_chars: int = SAMPLE_CHARS, passage: int = PASSAGE) -> dict[str, str]:
    """Language -> sample text, from rows where ``fold`` holds and text and language are given; text and language alone decide."""
    rows = docs.where(fold & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.xxhash64(F.lit("sample"), F.col(text_col)).alias("h"), F.col(text_col).alias("text"))
    begin = F.pmod("h", F.greatest(F.length("text") - passage, F.lit(1))).cast("int") + 1
    rows = rows.select("lang", "h", F.substring(F.col("text"), begin, F.lit(passage)).alias("text"))

    def first_texts(batches):
        # the smallest hashes of this task, copies once
        best: dict[str, dict[int, str]] = {}
        for b in batches:
            langs = b.column(0).to_pylist()
            hashes = b.column(1).to_pylist()
            for i, (g, h) in enumerate(zip(langs, hashes, strict=True)):
                mine = best.setdefault(g, {})
                if h not in mine:
                    mine[h] = b.column(2)[i].as_py()
                    if len(mine) >= 4 * sample_docs:
                        best[g] = {x: mine[x] for x in sorted(mine)[:sample_docs]}
        for g, mine in best.items():
            least = sorted(mine)[:sample_docs]
            yield pa.RecordBatch.from_arrays([pa.array([g] * len(least)), pa.array(least, pa.int64()), pa.array([mine[x] for x in least], pa.string())], ["lang", "h", "text"])

    found = rows.mapInArrow(first_texts, "lang string, h long, text string").dropDuplicates(["lang", "h"])
    # first inside parts of the hash, then over all: no task ranks what all tasks have sent
    for by in (["lang", F.pmod("h", F.lit(64))], ["lang"]):
        found = found.withColumn("r", F.row_number().over(Window.partitionBy(*by).orderBy("h"))).where(F.col("r") <= sample_docs)
    chosen: dict[str, list[tuple[int, str]]] = {}
    for r in found.select("lang", "r", "text").toLocalIterator():
        chosen.setdefault(r["lang"], []).append((r["r"], r["text"]))
    share = sample_chars // max(1, len(chosen))
    return {k: "\n".join(t for _, t in sorted(v))[:share] for k, v in sorted(chosen.items())}


def classes() -> np.ndarray:
    """The class of each code point, with letters as ``UNSEEN``."""
    table = np.full(sys.maxunicode + 1, OTHER, np.uint8)
    for i in range(sys.maxunicode + 1):
        c = chr(i)
        if c.isspace():
            table[i] = SPACE
        elif c.isalpha():
            table[i] = UNSEEN
        elif c.isdigit():
            table[i] = DIGIT
    return table


def alphabet(sample: str) -> dict[int, int]:
    """Symbol of each letter of a sample, by code point; both cases of a letter have one."""
    seen = Counter(c for c in sample.lower() if c.isalpha())
    ranked = [c for c, _ in sorted(seen.items(), key=lambda x: (-x[1], x[0]))]
    room = PAD - _FIRST
    own = ranked if len(ranked) <= room else ranked[: room - SHARED]
    symbol = {c: _FIRST + i for i, c in enumerate(own)}
    symbol |= {c: PAD - SHARED + ord(c) % SHARED for c in ranked[len(own) :]}
    every = {ord(c): s for c, s in symbol.items()}
    return every | {ord(c.upper()): s for c, s in symbol.items() if len(c.upper()) == 1 and c.upper().lower() == c}


def letters() -> np.ndarray:
    return np.fromiter((unicodedata.category(chr(i))[0] == "L" for i in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1)


def suffix_automaton(symbols: list[int]) -> np.ndarray:
    """Next state by state (rows) and symbol of the smallest automaton of all substrings, -1 where none; state 0 is the start."""
    blank = array("i", [-1]) * SYMBOLS
    step = array("i", blank)
    link, size, last = [-1], [0], 0
    for c in symbols:
        cur = len(link)
        step.extend(blank)
        link.append(0)
        size.append(size[last] + 1)
        p = last
        while p >= 0 and step[p * SYMBOLS + c] < 0:
            step[p * SYMBOLS + c] = cur
            p = link[p]
        if p >= 0:
            q = step[p * SYMBOLS + c]
            if size[p] + 1 == size[q]:
                link[cur] = q
            else:
                twin = len(link)
                step.extend(step[q * SYMBOLS : (q + 1) * SYMBOLS])
                link.append(link[q])
                size.append(size[p] + 1)
                link[q] = link[cur] = twin
                while p >= 0 and step[p * SYMBOLS + c] == q:
                    step[p * SYMBOLS + c] = twin
                    p = link[p]
        last = cur
    return np.array(step, np.int32).reshape(-1, SYMBOLS)


class CrossParser:
    """All languages' automata in one table: entry = next row start * 4, plus 1 where the step closes a phrase, plus 2 where its symbol is unseen."""

    def __init__(self, samples: dict[str, str]):
        self.names = sorted(k for k in samples if len(samples[k]) >= LEAST)
        base_class = classes()
        sets = [alphabet(samples[k]) for k in self.names]
        known = sorted(set().union(*sets)) if sets else []
        # code point -> place: three classes, unseen, then every letter of any sample
        self.place = base_class.astype(np.int32)
        self.place[known] = np.arange(_FIRST, _FIRST + len(known))
        self.symbol = np.full((len(self.names), _FIRST + len(known)), UNSEEN, np.uint8)
        self.symbol[:, :_FIRST] = np.arange(_FIRST)
        for k, own in enumerate(sets):
            self.symbol[k, self.place[list(own)]] = list(own.values())
        self.letter = np.packbits(letters())
        self.starts: list[int] = []
        base, tables = 0, []
        for k, name in enumerate(self.names):
            t = suffix_automaton(self.symbols(samples[name])[k].tolist())
            n = len(t)
            missing = t < 0
            absent = missing[0].copy()
            # a step that fails closes the phrase; its symbol opens the next one, or is a phrase of its own when unseen
            entry = np.where(missing, np.where(absent, 0, t[0])[None, :], t)
            entry += base
            entry *= SYMBOLS * 4
            entry += missing
            entry += 2 * absent[None, :].astype(np.int32)
            entry[0, absent] -= 1
            entry[:, PAD] = (np.arange(n) + base) * SYMBOLS * 4
            tables.append(entry.ravel())
            self.starts.append(base * SYMBOLS)
            base += n
        self.table = np.concatenate(tables) if tables else np.zeros(0, np.int32)
        self.weight = np.array([math.log2(len(samples[k])) for k in self.names])

    def __getstate__(self) -> dict:
        # most entries repeat the start's row: packed for the way to the workers and for the disk there
        return self.__dict__ | {k: zlib.compress(getattr(self, k).tobytes(), 1) for k in ("table", "place")}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state | {k: np.frombuffer(zlib.decompress(state[k]), np.int32) for k in ("table", "place")})

    def codes(self, text: str) -> np.ndarray:
        return np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)

    def symbols(self, text: str) -> np.ndarray:
        """Symbols of a text, a row a language."""
        return self.symbol[:, self.place[self.codes(text)]]

    def phrases(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(phrases found in the sample, symbols that it lacks) of each text (rows) in each language (columns)."""
        lens = np.array([len(t) for t in texts], np.int64)
        blocks = -(-lens // BLOCK)
        owner = np.repeat(np.arange(len(texts)), blocks)
        found = np.zeros((len(texts), len(self.names)), np.int64)
        if not len(owner) or not self.names:
            return found, found.copy()
        first = np.cumsum(blocks) - blocks
        place = self.place[self.codes("".join(texts))]
        begin = np.cumsum(lens) - lens
        to = np.arange(len(place)) + np.repeat(first * BLOCK - begin, lens)
        closed = np.zeros((len(self.names), len(owner)), np.int32)
        lacked = np.zeros_like(closed)
        grid = np.empty(len(owner) * BLOCK, np.uint8)
        for k, start in enumerate(self.starts):
            grid[:] = PAD
            grid[to] = self.symbol[k][place]
            by_step = np.ascontiguousarray(grid.reshape(-1, BLOCK).T)
            at = np.full(len(owner), start, np.int32)
            marks = np.zeros(len(owner), np.int32)
            for row in by_step:
                x = self.table[at + row]
                at = x >> 2
                # closed phrases in the low half, unseen symbols in the high one
                x &= 3
                marks += (x & 1) + ((x & 2) << 15)
            closed[k] = (marks & 0xFFFF) + (at != start)
            lacked[k] = marks >> 16
        for k in range(len(self.names)):
            found[:, k] = np.bincount(owner, weights=closed[k], minlength=len(texts))
        gone = np.stack([np.bincount(owner, weights=row, minlength=len(texts)) for row in lacked], axis=1).astype(np.int64)
        return found, gone

    def judge(self, texts: list[str]) -> tuple[list[str], list[float]]:
        tags, scores = [], []
        letter = np.unpackbits(self.letter)
        lo = 0
        while lo < len(texts):
            hi, n = lo, 0
            while hi < len(texts) and (hi == lo or n + len(texts[hi]) <= PIECE_CHARS):
                n += len(texts[hi])
                hi += 1
            part = texts[lo:hi]
            found, lacked = self.phrases(part)
            cost = found * self.weight[None, :] + lacked * LITERAL
            have = np.concatenate([[0], np.cumsum(letter[self.codes("".join(part))], dtype=np.int64)])
            ends = np.cumsum([len(t) for t in part])
            spoken = have[ends] > have[ends - np.array([len(t) for t in part])]
            for i, ok in enumerate(spoken.tolist()):
                if not ok or not self.names:
                    tags.append("und")
                    scores.append(0.0)
                    continue
                order = np.argsort(cost[i], kind="stable")
                tags.append(self.names[order[0]])
                scores.append(1.0 if len(order) < 2 else float(1.0 - cost[i][order[0]] / cost[i][order[1]]))
            lo = hi
        return tags, scores


class Packed:
    """A pickled parser that unpickles as the parser: the driver passes it on and never holds the tables themselves."""

    def __init__(self, blob: bytes):
        self.blob = blob

    def __reduce__(self):
        return pickle.loads, (self.blob,)


def packed_parser(spark, samples: dict[str, str]) -> Packed:
    """The parser of the samples, built by one task."""

    def build(batches):
        for _ in batches:
            pass
        blob = pickle.dumps(CrossParser(samples), protocol=5)
        # in parts: one value of a column has its bounds
        parts = [blob[i : i + (1 << 20)] for i in range(0, len(blob), 1 << 20)]
        for i, part in enumerate(parts):
            yield pa.RecordBatch.from_pydict({"i": pa.array([i], pa.int64()), "part": pa.array([part], pa.binary())})

    rows = spark.range(1).repartition(1).mapInArrow(build, "i long, part binary").collect()
    return Packed(b"".join(bytes(r["part"]) for r in sorted(rows, key=lambda r: r["i"])))


def identify(docs: DataFrame, samples: dict[str, str], text_col: str = "text", out: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """The rows of ``docs`` with the predicted language and a score: the share of phrase cost that the best language saves over the next."""
    docs = docs.drop(*(c for c in out if c != text_col))
    sent = docs.sparkSession.sparkContext.broadcast(packed_parser(docs.sparkSession, samples))
    at = docs.columns.index(text_col)

    def scan(batches):
        parser = sent.value
        for b in batches:
            for lo in range(0, b.num_rows, 1000):
                part = b.slice(lo, 1000)
                tags, scores = parser.judge([t or "" for t in part.column(at).to_pylist()])
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(tags, pa.string()), pa.array(scores, pa.float64())], [*part.schema.names, *out])

    schema = T.StructType([*docs.schema.fields, T.StructField(out[0], T.StringType()), T.StructField(out[1], T.DoubleType())])
    return docs.mapInArrow(scan, schema)


def held_out(id_col: str = "doc_id") -> Column:
    """The fold that no model may learn from."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(4)) == 2, F.lit(False))
