"""Array-at-a-time scanning of UTF-8 text: words, lines, n-gram fingerprints.

All functions work on one byte buffer that holds several documents back to back,
so the cost per document is a few array operations, not a Python loop over words.
A word is a longest run of bytes outside ``0x20, 0x09-0x0D``; UTF-8 keeps those
values for the white space itself, so byte runs equal the code-point runs of
``[^\\x20\\x09-\\x0D]+``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U64 = np.uint64
_M1, _M2, _K1, _K2 = U64(0xBF58476D1CE4E5B9), U64(0x94D049BB133111EB), U64(0x9E3779B97F4A7C15), U64(0xD6E8FEB86659FD93)
IS_WORD = np.ones(256, dtype=bool)
IS_WORD[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: bytes that start a code point
IS_LEAD = (np.arange(256) & 0xC0) != 0x80

PIECE_BYTES = 2 << 20


def mix(z: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser (shift-multiply rounds)."""
    z = z ^ (z >> U64(30))
    z *= _M1
    z ^= z >> U64(27)
    z *= _M2
    z ^= z >> U64(31)
    return z


@dataclass
class Piece:
    """Documents ``lo..hi`` of a batch: their bytes and the offsets of each in them."""

    lo: int
    hi: int
    buf: np.ndarray
    bounds: np.ndarray


def pieces(column: pa.Array | pa.ChunkedArray, limit: int = PIECE_BYTES) -> Iterator[Piece]:
    """Cut a string column into runs of documents of about ``limit`` bytes; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.large_string())
    column = column.cast(pa.large_string()).fill_null("")
    if not len(column):
        return
    _, offs, data = column.buffers()
    offs = np.frombuffer(offs, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < len(column):
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + limit, side="right")) - 1)
        hi = min(hi, len(column))
        yield Piece(lo, hi, data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo])
        lo = hi


@dataclass
class Runs:
    """Byte runs (words or lines) of a piece: start and end offsets and the document of each."""

    starts: np.ndarray
    ends: np.ndarray
    doc: np.ndarray


def words(piece: Piece) -> Runs:
    buf, bounds = piece.buf, piece.bounds
    n = len(buf)
    if not n:
        z = np.zeros(0, np.int64)
        return Runs(z, z, z)
    inside = IS_WORD[buf]
    fresh = inside.copy()
    fresh[1:] &= ~inside[:-1]
    cut = bounds[1:-1]
    cut = cut[(cut > 0) & (cut < n)]
    fresh[cut] = inside[cut]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[cut - 1] = inside[cut - 1]
    starts = np.flatnonzero(fresh)
    return Runs(starts, np.flatnonzero(last) + 1, np.searchsorted(bounds, starts, side="right") - 1)


def lines(piece: Piece) -> Runs:
    r"""Runs between ``\n`` bytes and document edges, empty ones included (empty documents: none)."""
    buf, bounds = piece.buf, piece.bounds
    full = np.flatnonzero(np.diff(bounds))
    nl = np.flatnonzero(buf == 0x0A)
    starts = np.concatenate([bounds[full], nl + 1])
    ends = np.concatenate([nl, bounds[full + 1]])
    doc = np.concatenate([full, np.searchsorted(bounds, nl, side="right") - 1])
    order = np.lexsort((starts, doc))
    starts, doc = starts[order], doc[order]
    ends = np.sort(ends, kind="stable")
    return Runs(starts, ends, doc)


def _blocks(buf: np.ndarray, runs: Runs) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(eight-byte blocks of all runs in order, zero-filled at a run's end; place of each in its run; first block of each run; blocks of each)."""
    lens = runs.ends - runs.starts
    count = (lens + 7) >> 3
    first = np.cumsum(count) - count
    place = np.arange(int(count.sum()), dtype=np.int64) - np.repeat(first, count)
    # every eight bytes of the buffer as one number, read at any offset
    wide = np.ndarray(len(buf) + 1, "<u8", np.concatenate([buf, np.zeros(8, np.uint8)]), 0, (1,))
    value = wide[np.repeat(runs.starts, count) + (place << 3)]
    # what lies beyond the run's end is not part of it
    left = np.minimum(np.repeat(lens, count) - (place << 3), 8).astype(U64)
    value &= ~U64(0) >> (U64(64) - (left << U64(3)))
    return value, place, first, count


def _block_hashes(value: np.ndarray, place: np.ndarray, first: np.ndarray, lens: np.ndarray) -> np.ndarray:
    mixed = mix((value ^ mix((place.astype(U64) + U64(1)) * _K1)) * _K2)
    out = np.zeros(len(lens), dtype=U64)
    some = np.flatnonzero(lens)
    if len(some):
        out[some] = np.add.reduceat(mixed, first[some])
    return mix(out + lens.astype(U64) * _K1)


def run_hashes(buf: np.ndarray, runs: Runs, lower: bool = False) -> np.ndarray:
    """A 64-bit fingerprint of the bytes of each run; equal bytes, equal value, wherever they lie.

    Each block of eight bytes is mixed with a key of its place before the blocks are summed, so no arrangement of
    equal blocks cancels out, as it can in a polynomial modulo a power of two.
    """
    value, place, first, _ = _blocks(LOWER[buf] if lower else buf, runs)
    return _block_hashes(value, place, first, runs.ends - runs.starts)


def intern(buf: np.ndarray, runs: Runs, lower: bool = False) -> np.ndarray:
    """A number for each run, the same for two runs just where their bytes are the same.

    Runs are grouped by fingerprint and every one is compared with the first of its group; should two
    differ, a dictionary of the bytes themselves numbers all.
    """
    if lower:
        buf = LOWER[buf]
    value, place, first, count = _blocks(buf, runs)
    lens = runs.ends - runs.starts
    _, head, ids = np.unique(_block_hashes(value, place, first, lens), return_index=True, return_inverse=True)
    head = head[ids]
    if np.array_equal(lens, lens[head]) and np.array_equal(value, value[np.repeat(first[head], count) + place]):
        return ids.astype(np.int64)
    raw, seen = buf.tobytes(), {}
    return np.fromiter((seen.setdefault(raw[s:e], len(seen)) for s, e in zip(runs.starts.tolist(), runs.ends.tolist(), strict=True)), np.int64, len(lens))


def pair_ids(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A number for each pair of numbers under 2^31, the same just where the pairs are the same."""
    return np.unique((a.astype(np.int64) << 32) | b, return_inverse=True)[1].astype(np.int64)


def exact_ngrams(ids: np.ndarray, n: int) -> np.ndarray:
    """A number for each run of ``n`` items of an interned sequence, the same just where the items are the same."""
    have, h = 1, ids
    for want in ladder(n)[1:]:
        shift = want - have
        size = len(h) - shift
        if size <= 0:
            return np.zeros(0, np.int64)
        h, have = pair_ids(h[:size], h[shift:]), want
    return h


def combine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Ordered combination of two fingerprints of equal-length word runs."""
    return mix(a * _K1 + (b ^ (b >> U64(29))) * _K2 + U64(0x632BE59BD9B4E019))


def ladder(length: int, base: int | None = None) -> list[int]:
    """Window lengths of a doubling schedule that ends at ``length``: each is at most twice the last."""
    steps = [length]
    low = max(1, base or 1)
    while steps[-1] > low:
        steps.append((steps[-1] + 1) // 2)
    return steps[::-1]


def widen(h: np.ndarray, have: int, want: int) -> np.ndarray:
    """Fingerprints of windows of ``want`` words from those of ``have`` words, ``have <= want <= 2 * have``."""
    shift = want - have
    n = len(h) - shift
    if n <= 0:
        return np.zeros(0, dtype=U64)
    return combine(h[:n], h[shift:])


def ngrams(wh: np.ndarray, n: int) -> np.ndarray:
    """Fingerprints of all runs of ``n`` words in the array, document edges ignored."""
    have, h = 1, wh
    for want in ladder(n)[1:]:
        h, have = widen(h, have, want), want
    return h


def within(doc: np.ndarray, n: int) -> np.ndarray:
    """True where the run of ``n`` words that starts there ends in the same document."""
    if len(doc) < n:
        return np.zeros(0, dtype=bool)
    return doc[: len(doc) - n + 1] == doc[n - 1 :]


def cover(starts_at: np.ndarray, n_words: int, n: int) -> np.ndarray:
    """Words covered by windows of ``n`` words that start at the given indexes."""
    edge = np.zeros(n_words + 1, dtype=np.int32)
    np.add.at(edge, starts_at, 1)
    np.add.at(edge, np.minimum(starts_at + n, n_words), -1)
    return np.cumsum(edge[:-1]) > 0
