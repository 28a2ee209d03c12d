"""Cutting texts into the units inside which a byte-pair tokenizer works, and caches of their codes.

A tokenizer of the two JSON files splits a text by a fixed pattern and merges inside each part alone, so a text's tokens are
its parts' tokens in a row, and a part's tokens can be looked up.  The cut below is made with a regular expression where that
is known to agree with the library's own (Latin text and common marks); any other text goes to the library whole, so results
are the library's for every input.
"""

from __future__ import annotations

import os
import re
from array import array

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

# letters of the safe range, as regular-expression classes; U+00AA and U+00BA are letters, U+00B2/B3/B9/BC-BE are numbers
_L = "A-Za-zªµºÀ-ÖØ-öø-ž"
_N = "0-9²³¹¼-¾"
_S = " \t\n\r\x0b\x0c"
#: a text of these alone is cut here
SAFE = re.compile(r"[\t\n\r -~¡-¬®-įĲ-ňŊ-ž–—‘’“”…]*")
# fixed values: the contractions and classes of the public pattern of the two vocabularies
_CONTRACT = "'s|'t|'re|'ve|'m|'ll|'d"
BYTE_UNITS = re.compile(rf"{_CONTRACT}| ?[{_L}]+| ?[{_N}]+| ?[^{_S}{_L}{_N}]+|[{_S}]+(?![^{_S}])|[{_S}]+")
WORD_UNITS = re.compile(rf"{_CONTRACT}|[{_L}]+|[{_N}]|[^{_S}{_L}{_N}]+")
#: entries of at most MAX_UNIT characters each: some tens of megabytes a worker
MAX_CACHE = 400_000
MAX_UNIT = 64


def plain(text: str) -> bool:
    """True where the pattern here cuts as the library does and no special token can be in the text."""
    return "<|" not in text and SAFE.fullmatch(text) is not None


def vocabulary_path(name: str) -> str:
    """Place of a public vocabulary file: an existing path as it is, else by name."""
    if os.path.exists(name):
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


def unit_ids(tok):
    """The token ids of one unit, packed as 32-bit numbers: merges alone, since a unit is lower-cased, composed and cut already."""
    from tokenizers import pre_tokenizers

    letters, merges = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False).pre_tokenize_str, tok.model.tokenize

    def ids(unit: str) -> bytes:
        # printable ASCII stands for itself in the alphabet of bytes
        return array("I", [t.id for t in merges(unit if unit.isascii() else letters(unit)[0][0])]).tobytes()

    return ids


class Misses(dict):
    """A bounded cache that computes what it lacks; long units are computed each time.

    Full, it stays as it is while four times as many misses go by, so that units met early, the frequent ones, are not lost at once; then it starts anew.
    """

    def __init__(self, compute, start=None, limit: int = MAX_CACHE):
        super().__init__(start or {})
        self.compute, self.limit, self.passed = compute, limit, 0

    def __missing__(self, unit):
        value = self.compute(unit)
        if len(unit) <= MAX_UNIT:
            if len(self) < self.limit:
                self[unit] = value
            else:
                self.passed += 1
                if self.passed >= 4 * self.limit:
                    self.clear()
                    self.passed = 0
        return value


_tokenizers: dict[str, object] = {}


def tokenizer(name: str):
    """The library's tokenizer for a vocabulary file, loaded once a worker."""
    if name not in _tokenizers:
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(vocabulary_path(name))
        t.no_truncation()
        t.no_padding()
        _tokenizers[name] = t
    return _tokenizers[name]
