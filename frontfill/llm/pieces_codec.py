"""SentencePiece-style encoding and decoding by Viterbi over an Aho-Corasick automaton (operator 10).

The automaton of all vocabulary pieces reads a text once; at each place its output links name every piece that ends there, and the best score
up to the place is relaxed over them.  Characters that no piece holds become byte pieces.  No piece crosses the step from a
character to a following word mark or to a character without a piece, so a text falls apart at those places and a unit's
best path can be cached; the result is the best path of the whole text.

Scores: a unigram model's own are summed.  A merge-ranked (BPE) vocabulary has ranks in their place, whose sum means nothing.  There the step at a
place relaxes over the same output links by another rule: a piece may end there when merging by rank leaves it and the piece before it apart
as they are.  A sequence is what merging gives just where all its neighbours are so, and the last piece of every prefix is unique, hence the pass finds
the library's own ids; whether two pieces stay apart is looked up in a bounded cache.

Defined results: null and empty texts have no pieces; a text that holds the word mark itself decodes with spaces, as the library does;
repeated rows are separate; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm.units import Misses, vocabulary_path

VOCABULARY = "piece_bpe_32k.model"
MARK = "▁"
LOW = -1e9


def merge(text: str, rank: dict[str, float], made: bool = False) -> list[str]:
    """Merging by rank, by definition: the best-ranked neighbours that make a piece are joined, the leftmost first, until none do.

    ``made`` asks for the two parts that the last join puts together, and for none where it does not leave one piece.
    """
    none = math.inf
    parts = list(text)
    pairs = [rank.get(x + y, none) for x, y in zip(parts, parts[1:], strict=False)]
    while pairs:
        best = min(pairs)
        if best == none:
            break
        k = pairs.index(best)
        if made and len(pairs) == 1:
            return parts
        parts[k : k + 2] = [parts[k] + parts[k + 1]]
        del pairs[k]
        if k:
            pairs[k - 1] = rank.get(parts[k - 1] + parts[k], none)
        if k < len(pairs):
            pairs[k] = rank.get(parts[k] + parts[k + 1], none)
    return [] if made else parts


class PieceModel:
    """A vocabulary with scores, its automaton, and the cache of unit paths."""

    def __init__(self, pieces: list[str], scores: list[float], byte_ids: list[int], usable: list[bool], merged: bool = False):
        import ahocorasick

        self.pieces, self.byte_ids = pieces, byte_ids
        self.score = scores
        self.auto = ahocorasick.Automaton()
        chars: set[str] = set()
        for i, p in enumerate(pieces):
            if usable[i] and p:
                self.auto.add_word(p, (i, len(p), scores[i], p))
                chars |= set(p)
        # a character of some piece that is none itself stays as it is until bytes stand for it
        for c in chars - {p for i, p in enumerate(pieces) if usable[i]}:
            self.auto.add_word(c, (-1, 1, LOW, c))
        self.auto.make_automaton()
        known = "".join(re.escape(c) for c in sorted(chars - {MARK})) or MARK
        self.units = re.compile(f"{MARK}*[{known}]+|{MARK}+|[^{known}{MARK}]+")
        self.known = re.compile(f"[{known}{MARK}]")
        self.byte_of = {i: b for b, i in enumerate(byte_ids)}
        self.id_of = {p: i for i, p in enumerate(pieces) if usable[i] and p}
        self.merged = merged
        self.rank = {p: -scores[i] for p, i in self.id_of.items()}
        self.made = Misses(lambda p: merge(p, self.rank, made=True), limit=400_000)
        self.whole = Misses(lambda p: len(p) == 1 or bool(self.made[p]), limit=400_000)
        self.apart = Misses(lambda ab: self.stay_apart(*ab), limit=400_000)
        walk = self.merged_path if merged else self.path
        self.cache = Misses(lambda u: np.array(walk(u), np.uint32).tobytes(), limit=200_000)

    @classmethod
    def load(cls, name: str = VOCABULARY) -> PieceModel:
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=vocabulary_path(name))
        n = m.get_piece_size()
        pieces = [m.id_to_piece(i) for i in range(n)]
        usable = [not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i) or m.is_unused(i)) for i in range(n)]
        scores = [m.get_score(i) for i in range(n)]
        # whole numbers are ranks: a unigram model's are logarithms of shares
        return cls(pieces, scores, [m.piece_to_id(f"<0x{b:02X}>") for b in range(256)], usable, all(s == int(s) for s in scores))

    def path(self, unit: str) -> list[int]:
        """Ids of the best segmentation of one unit."""
        n = len(unit)
        best, back = [0.0] + [LOW * (n + 1)] * n, [None] * (n + 1)
        found = iter(self.auto.iter(unit)) if unit else iter(())
        nxt = next(found, None)
        for end in range(1, n + 1):
            # one character by its bytes, where nothing better ends here
            top, how = best[end - 1] + LOW, -1
            while nxt is not None and nxt[0] == end - 1:
                i, size, score, _ = nxt[1]
                s = best[end - size] + score
                if s > top or (s == top and how >= 0 and i < how):
                    top, how = s, i
                nxt = next(found, None)
            best[end], back[end] = top, how
        out: list[int] = []
        at = n
        while at:
            i = back[at]
            if i < 0:
                out += [self.byte_ids[b] for b in reversed(unit[at - 1].encode())]
                at -= 1
            else:
                out.append(i)
                at -= len(self.pieces[i])
        return out[::-1]

    def stay_apart(self, a: str, b: str) -> bool:
        """Whether merging leaves two whole pieces side by side.

        Back in time from the finished pieces: undoing the later of the two last merges gives the neighbours that met at the border before it.
        If any such two make a piece of a better rank than the merge that came next there, they would have been joined instead.
        """
        rank, made = self.rank, self.made
        early = -math.inf
        made_a, made_b = (rank[a] if len(a) > 1 else early), (rank[b] if len(b) > 1 else early)
        bound, tie = math.inf, False
        while True:
            r = rank.get(a + b)
            if r is not None and (r < bound or (tie and r == bound)):
                return False
            if made_a == early and made_b == early:
                return True
            if made_a > made_b:
                # leftmost first: a join across the border comes after an equal one inside the left piece
                bound, tie = made_a, False
                a = made[a][1]
                made_a = rank[a] if len(a) > 1 else early
            else:
                bound, tie = made_b, True
                b = made[b][0]
                made_b = rank[b] if len(b) > 1 else early

    def merged_path(self, unit: str) -> list[int]:
        """Ids that merging by rank gives one unit, found left to right."""
        if not self.known.match(unit):
            # characters of no piece: the cut puts them in units of their own
            return [self.byte_ids[b] for b in unit.encode()]
        n = len(unit)
        last: list[str | None] = [None] * (n + 1)
        last[0] = ""
        whole, apart = self.whole, self.apart
        for at, (_, size, _, p) in self.auto.iter(unit):
            if last[at + 1] is None:
                before = last[at + 1 - size]
                if before is not None and whole[p] and (not before or apart[before, p]):
                    last[at + 1] = p
        out: list[int] = []
        at = n
        while at:
            p = last[at]
            i = self.id_of.get(p)
            out += [self.byte_ids[b] for b in reversed(p.encode())] if i is None else [i]
            at -= len(p)
        return out[::-1]

    def encode(self, text: str) -> bytes:
        """Ids as little-endian 32-bit numbers."""
        if not text:
            return b""
        return b"".join(map(self.cache.__getitem__, self.units.findall(MARK + text.replace(" ", MARK))))

    def decode(self, ids) -> str:
        """The text of a list of ids; byte pieces are joined, the leading mark goes."""
        out: list[bytes] = []
        for i in ids:
            b = self.byte_of.get(i)
            out.append(bytes([b]) if b is not None else self.pieces[i].encode())
        text = b"".join(out).decode("utf-8", "replace").replace(MARK, " ")
        return text[1:] if text.startswith(" ") else text


_models: dict[str, PieceModel] = {}


def model(name: str = VOCABULARY) -> PieceModel:
    if name not in _models:
        _models[name] = PieceModel.load(name)
    return _models[name]


def encode_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, with_ids: bool = True) -> DataFrame:
    """``doc_id, n_pieces, n_byte_pieces, ids_crc32, round_trip`` and, if asked for, ``ids`` (array<int>) of every row."""

    def scan(batches):
        m = model(vocabulary)
        is_byte = np.zeros(len(m.pieces), bool)
        is_byte[m.byte_ids] = True
        for b in batches:
            keys = b.column(0)
            for lo in range(0, b.num_rows, 500):
                counts, low, crc, same, flat = [], [], [], [], []
                for t in b.column(1).slice(lo, 500).to_pylist():
                    raw = m.encode(t or "")
                    ids = np.frombuffer(raw, np.uint32)
                    counts.append(len(ids))
                    low.append(int(is_byte[ids].sum()))
                    crc.append(zlib.crc32(raw))
                    same.append(m.decode(ids.tolist()) == (t or ""))
                    if with_ids:
                        flat.append(ids.astype(np.int32))
                cols = [keys.slice(lo, 500), pa.array(counts, pa.int64()), pa.array(low, pa.int64()), pa.array(crc, pa.int64()), pa.array(same, pa.bool_())]
                if with_ids:
                    offs = np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)
                    cols.append(pa.ListArray.from_arrays(pa.array(offs, pa.int32()), pa.array(np.concatenate(flat), pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_pieces", "n_byte_pieces", "ids_crc32", "round_trip", *["ids"] * with_ids])

    schema = "doc_id long, n_pieces long, n_byte_pieces long, ids_crc32 long, round_trip boolean" + ", ids array<int>" * with_ids
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(scan, schema)


def decode_documents(encoded: DataFrame, vocabulary: str = VOCABULARY, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``doc_id, text`` from ``ids`` (null ids: empty text)."""

    def scan(batches):
        m = model(vocabulary)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([m.decode(x or []) for x in b.column(1).to_pylist()], pa.string())], ["doc_id", "text"])

    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(scan, "doc_id long, text string")
